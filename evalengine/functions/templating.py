"""Prompt templates compiled to one Column.

Syntax: ``{{ column }}``, ``{{ column | filter }}`` or ``{{ column | filter(argument) }}``; ``{% if column %} ... {% endif %}``
keeps its body where the column is neither null nor empty; ``{% each column %} ... {{ item }} ... {% endeach %}``
repeats its body over an array. The template is read once on the driver.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TOKEN = re.compile(r"\{\{\s*(\w+)((?:\s*\|\s*\w+(?:\([^)]*\))?)*)\s*\}\}|\{%\s*(if|each)\s+(\w+)\s*%\}|\{%\s*(endif|endeach)\s*%\}")
FILTERS = {
    "trim": lambda c: F.trim(c), "lower": lambda c: F.lower(c), "upper": lambda c: F.upper(c), "json": lambda c: F.to_json(c),
    "truncate": lambda c, k: F.substring(c, 1, int(k)), "default": lambda c, x: F.coalesce(c, F.lit(x)), "join": lambda c, x=" ": F.array_join(c, x),
}


class TemplateError(ValueError):
    pass


def _slot(column: Column, filters: str, on_null: str, name: str) -> Column:
    for f, argument in re.findall(r"(\w+)(?:\(([^)]*)\))?", filters or ""):
        if f not in FILTERS:
            raise TemplateError(f"unknown filter {f}")
        column = FILTERS[f](column, argument.strip("'\"")) if argument else FILTERS[f](column)
    text = column.cast("string")
    if on_null == "empty":
        return F.coalesce(text, F.lit(""))
    if on_null == "error":
        return F.coalesce(text, F.raise_error(F.lit(f"null in slot {name}")))
    return text


def compiled(template: str, columns: list[str], on_null: str = "empty") -> Column:
    """The template as a Column; names that are not among ``columns`` are errors before any job runs."""
    parts, pos, at = list(TOKEN.finditer(template)), 0, 0

    def repeated(begun: tuple[int, int]):
        def each(x: Column) -> Column:
            nonlocal pos, at
            pos, at = begun
            return body("endeach", x)

        return each

    def body(until: str | None, item: Column | None) -> Column:
        nonlocal pos, at
        out: list[Column] = []
        while at < len(parts):
            m = parts[at]
            at += 1
            if m.start() > pos:
                out.append(F.lit(template[pos : m.start()]))
            pos = m.end()
            if m[1]:
                if m[1] == "item" and item is not None:
                    column = item
                elif m[1] in columns:
                    column = F.col(m[1])
                else:
                    raise TemplateError(f"no column {m[1]}")
                out.append(_slot(column, m[2], on_null, m[1]))
            elif m[3]:
                name = m[4]
                if name not in columns:
                    raise TemplateError(f"no column {name}")
                if m[3] == "if":
                    inside = body("endif", item)
                    out.append(F.when(F.length(F.col(name).cast("string")) > 0, inside).otherwise(""))
                else:
                    begun = (pos, at)

                    out.append(F.array_join(F.transform(F.col(name), repeated(begun)), ""))
            elif m[5] != until:
                raise TemplateError(f"unexpected {m[5]}")
            else:
                return F.concat(*out) if out else F.lit("")
        if until:
            raise TemplateError(f"missing {until}")
        out.append(F.lit(template[pos:]))
        return F.concat(*out)

    return body(None, None)


def render(df: DataFrame, template: str, out: str = "prompt", on_null: str = "empty") -> DataFrame:
    return df.withColumn(out, compiled(template, df.columns, on_null))


def render_rowwise(df: DataFrame, fill, out: str = "prompt") -> DataFrame:
    """For templates outside the syntax: ``fill(row: dict) -> str`` over Arrow batches."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            b[out] = [fill(r) for r in b.to_dict("records")]
            yield b

    return df.mapInPandas(run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema), f"{out} string"]))


def estimated_tokens(text: Column, rule: str = "chars4") -> Column:
    return F.ceil(F.length(text) / 4).cast("int") if rule == "chars4" else F.size(F.filter(F.split(text, r"\s+"), lambda w: w != ""))


def thread_prompts(turns: DataFrame, thread: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Each turn with all turns before it and itself as one prompt."""
    w = Window.partitionBy(thread).orderBy(turn).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return turns.withColumn("prompt", F.array_join(F.collect_list(F.concat_ws(": ", role, text)).over(w), "\n"))
