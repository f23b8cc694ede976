"""The scalar metrics as SQL functions of a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.functions.lexical import common_subsequence

_WORDS = "filter(split(trim(regexp_replace(regexp_replace(lower({}), '[!-/:-@\\\\[-`{{-~]', ''), '[ \\\\t\\\\n\\\\r]+', ' ')), ' '), w -> w <> '')"


def install(spark: SparkSession) -> None:
    """Temporary functions: ``eval_words``, ``eval_exact_match``, ``eval_contains``, ``eval_token_f1`` (SQL bodies, so that they
    are planned like any expression) and ``eval_rouge_l`` (Arrow batches)."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION eval_words(t STRING) RETURNS ARRAY<STRING> RETURN {_WORDS.format('t')}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION eval_exact_match(a STRING, b STRING) RETURNS DOUBLE RETURN CAST(array_join(eval_words(a), ' ') = array_join(eval_words(b), ' ') AS DOUBLE)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION eval_contains(a STRING, b STRING) RETURNS DOUBLE RETURN CAST(contains(a, b) AS DOUBLE)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION eval_token_f1(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN size(eval_words(a)) + size(eval_words(b)) = 0 THEN 1.0D ELSE "
        "2.0D * coalesce(aggregate(array_distinct(eval_words(a)), 0, (s, d) -> s + least(size(filter(eval_words(a), x -> x = d)), size(filter(eval_words(b), x -> x = d)))), 0) / (size(eval_words(a)) + size(eval_words(b))) END"
    )

    @F.pandas_udf("double")
    def rouge(a: pd.Series, b: pd.Series) -> pd.Series:
        one = lambda x, y: None if x is None or y is None else float(len(x) == len(y)) if not len(x) or not len(y) else 2 * common_subsequence(list(x), list(y)) / (len(x) + len(y))
        return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    spark.udf.register("eval_rouge_l", rouge)


def bag(tokens: Column) -> Column:
    """A bag of tokens as a map from token to count."""
    return F.map_from_entries(F.transform(F.array_distinct(tokens), lambda d: F.struct(d, F.size(F.filter(tokens, lambda x: x == d)))))


def overlap(a: Column, b: Column) -> Column:
    """Size of the intersection of two bags."""
    both = F.map_zip_with(a, b, lambda _, x, y: F.least(F.coalesce(x, F.lit(0)), F.coalesce(y, F.lit(0))))
    return F.aggregate(F.map_values(F.map_filter(both, lambda _, n: n > 0)), F.lit(0), lambda s, n: s + n)


def row_wise(df: DataFrame, answer, out: str, *columns: str) -> DataFrame:
    """The baseline without batches: one Python call a row."""
    return df.withColumn(out, F.udf(answer, "string")(*columns))
