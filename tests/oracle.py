"""Compare a query with its SQL in DuckDB: rows, column names and values, in any order."""

from __future__ import annotations

import math
import os
from datetime import datetime
from decimal import Decimal

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 5) + 0.0
    if isinstance(v, Decimal):
        return round(float(v), 5)
    if isinstance(v, datetime):
        return v.replace(tzinfo=None).isoformat()
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


def rows(names: list[str], data) -> list:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in data), key=repr)


def expected(sql: str, folder: str) -> tuple[list[str], list]:
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in TABLES:
        if os.path.exists(f"{folder}/{t}.parquet"):
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    r = c.execute(sql)
    names = [x[0] for x in r.description]
    return sorted(names), rows(names, r.fetchall())


def found(df) -> tuple[list[str], list]:
    return sorted(df.columns), rows(df.columns, df.collect())
