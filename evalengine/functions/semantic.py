"""Vector metrics in double precision."""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    """Cosine; null where a vector is zero."""
    n = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(n > 0, dot(a, b) / n)


def token_row(token: Column, rows: int) -> Column:
    """The stand-in encoder's vector number of a token: its digest modulo the table's rows."""
    return (F.conv(F.substring(F.sha2(token, 256), 1, 8), 16, 10).cast("bigint") % rows).cast("bigint")


def hashed_sentences(df: DataFrame, id_col: str, tokens: Column, vectors: DataFrame, rows: int) -> DataFrame:
    """``id_col``, ``vector``: the mean of the token vectors. The vector table is fixed in size and broadcast by the planner."""
    said = df.select(id_col, F.explode(tokens).alias("t")).groupBy(id_col, token_row(F.col("t"), rows).alias("vec_id")).agg(F.count("*").alias("k"))
    parts = said.join(vectors.select("vec_id", F.posexplode("embedding").alias("d", "x")), "vec_id").groupBy(id_col, "d").agg((F.sum(F.col("k") * F.col("x").cast("double")) / F.sum("k")).alias("x"))
    return parts.groupBy(id_col).agg(F.transform(F.sort_array(F.collect_list(F.struct("d", "x"))), lambda s: s["x"]).alias("vector"))


def greedy_match(df: DataFrame, id_col: str, mine: Column, theirs: Column, vectors: DataFrame, rows: int) -> DataFrame:
    """Token matching: each token takes its best cosine on the other side; precision, recall and F of the means."""
    unit = vectors.select("vec_id", F.transform("embedding", lambda x: x.cast("double") / F.sqrt(dot(F.col("embedding"), F.col("embedding")))).alias("v"))

    def side(tokens: Column, name: str) -> DataFrame:
        said = df.select(id_col, F.explode(tokens).alias("t")).groupBy(id_col, token_row(F.col("t"), rows).alias("vec_id")).agg(F.count("*").alias(f"k_{name}"))
        return said.join(unit, "vec_id").select(id_col, F.col("vec_id").alias(name), f"k_{name}", F.col("v").alias(f"v_{name}"))

    a, b = side(mine, "a"), side(theirs, "b")
    pairs = a.join(b, id_col).select(id_col, "a", "b", "k_a", "k_b", dot(F.col("v_a"), F.col("v_b")).alias("c"))
    p = pairs.groupBy(id_col, "a", "k_a").agg(F.max("c").alias("c")).groupBy(id_col).agg((F.sum(F.col("k_a") * F.col("c")) / F.sum("k_a")).alias("precision"))
    r = pairs.groupBy(id_col, "b", "k_b").agg(F.max("c").alias("c")).groupBy(id_col).agg((F.sum(F.col("k_b") * F.col("c")) / F.sum("k_b")).alias("recall"))
    return p.join(r, id_col).withColumn("f1", F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


@functools.lru_cache(100_000)
def _digest(token: str) -> int:
    return int(hashlib.sha256(token.encode()).hexdigest()[:8], 16)


def _unit_table(vectors: str) -> np.ndarray:
    """The stand-in encoder's table, a row for each ``vec_id`` in order, scaled to length 1."""
    table = SparkSession.active().read.parquet(vectors).select("vec_id", "embedding").orderBy("vec_id").toArrow().column("embedding")
    m = np.array(table.to_pylist(), np.float64)
    length = np.sqrt((m * m).sum(axis=1, keepdims=True))
    return np.divide(m, length, out=np.zeros_like(m), where=length > 0)


def sentence_cosine(mine: Column, theirs: Column, vectors: str) -> Column:
    """Cosine of the mean token vectors of two texts; null where one has no vector."""
    shared = SparkSession.active().sparkContext.broadcast(_unit_table(vectors))

    def mean(tokens: list[str]) -> np.ndarray:
        return shared.value[[_digest(t) % len(shared.value) for t in tokens]].sum(axis=0)

    def one(a: list[str] | None, b: list[str] | None) -> float | None:
        if a is None or b is None or not len(a) or not len(b):
            return None
        x, y = mean(a), mean(b)
        n = float(np.linalg.norm(x) * np.linalg.norm(y))
        return float(x @ y) / n if n else None

    @F.pandas_udf("double")
    def scored(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([one(s, t) for s, t in zip(a, b, strict=True)], dtype="float64")

    return scored(mine, theirs)


def token_match_parts(mine: Column, theirs: Column, vectors: str) -> Column:
    """``greedy_match`` in Arrow batches, a matrix product an example, with the encoder's whole table (``vectors`` is its
    path) on each worker: precision, recall and f1, null where a side is null.

    An empty side matches an empty one only; the vector of a token is the row of its digest in order of ``vec_id``.
    """
    shared = SparkSession.active().sparkContext.broadcast(_unit_table(vectors))

    def one(a: list[str] | None, b: list[str] | None) -> tuple[float | None, float | None, float | None]:
        if a is None or b is None:
            return None, None, None
        if not len(a) or not len(b):
            return (float(len(a) == len(b)),) * 3
        (x, i), (y, j) = (np.unique([_digest(t) % len(shared.value) for t in s], return_counts=True) for s in (a, b))
        c = shared.value[x] @ shared.value[y].T
        p, r = float(c.max(axis=1) @ i / len(a)), float(c.max(axis=0) @ j / len(b))
        return p, r, 2 * p * r / (p + r) if p + r else 0.0

    @F.pandas_udf("precision double, recall double, f1 double")
    def scored(a: pd.Series, b: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([one(s, t) for s, t in zip(a, b, strict=True)], columns=["precision", "recall", "f1"], dtype="float64")

    return scored(mine, theirs)


def token_match(mine: Column, theirs: Column, vectors: str) -> Column:
    """The F of ``token_match_parts``."""
    return token_match_parts(mine, theirs, vectors)["f1"]
