"""What is done with scores: alignment of runs, matrices, leaderboards, trends, threads, files, views and counters."""

from __future__ import annotations

import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F


def alignment(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """How the ids of two runs meet: in both, only in the first, only in the second."""
    x, y = (d.select(key).distinct().withColumn(n, F.lit(1)) for d, n in ((a, "_a"), (b, "_b")))
    met = x.join(y, key, "full_outer").select(F.when(F.col("_b").isNull(), "only_a").when(F.col("_a").isNull(), "only_b").otherwise("both").alias("side"))
    return met.groupBy("side").agg(F.count("*").alias("ids"))


def common(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    return a.select(key).intersect(b.select(key))


def gap(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Rows of the first run that the second lacks, repeats counted."""
    return a.select(key).exceptAll(b.select(key))


def labelled(df: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    return df.join(labels.select(key), key, "left_semi")


def paired_groups(a: DataFrame, b: DataFrame, key: str, value: str) -> DataFrame:
    """Two runs' values of a key side by side in one Python group: sizes and the difference of means. A key is small (a
    thread, a query); its rows meet by cogroup, so neither side is collected into an array."""

    def both(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        who = (x if len(x) else y)[key].iloc[0]
        gap = float(x[value].mean() - y[value].mean()) if len(x) and len(y) else None
        return pd.DataFrame({key: [who], "n_a": [len(x)], "n_b": [len(y)], "gap": pd.Series([gap], dtype="float64")})

    kind = dict(a.dtypes)[key]
    return a.select(key, value).groupBy(key).cogroup(b.select(key, value).groupBy(key)).applyInPandas(both, f"{key} {kind}, n_a long, n_b long, gap double")


def matrix(scores: DataFrame, row: str, column: str, value: str, columns: list[str]) -> DataFrame:
    """Mean value by row and column; the columns are named, so the plan is one aggregate."""
    return scores.groupBy(row).pivot(column, columns).agg(F.avg(value))


def long(wide: DataFrame, ids: list[str], metrics: list[str]) -> DataFrame:
    return wide.unpivot(ids, metrics, "metric", "value")


def leaderboard(scores: DataFrame, by: list[str], value: str) -> DataFrame:
    """Every ranking function over the scores of a group; ties share a rank, rows of a tie are numbered by the rest."""
    w = Window.partitionBy(*by).orderBy(F.desc(value))
    return scores.withColumns({"rank": F.rank().over(w), "dense": F.dense_rank().over(w), "quarter_share": F.cume_dist().over(w), "percent": F.percent_rank().over(w)})


def trend(df: DataFrame, by: str, order: str, value: str | Column) -> DataFrame:
    """Each row beside the one before and after it and the group's first and second."""
    w = Window.partitionBy(by).orderBy(order)
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    v = F.col(value) if isinstance(value, str) else value
    return df.withColumns({"before": F.lag(v).over(w), "after": F.lead(v).over(w), "first": F.first(v).over(whole), "second": F.nth_value(v, 2).over(whole)})


def thread_scores(turns: DataFrame, thread: str, order: str, value: str) -> DataFrame:
    """Scores of a thread from its scored turns: how many, mean, worst, last, and the running mean's lowest point."""
    w = Window.partitionBy(thread).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ran = turns.withColumn("_running", F.avg(value).over(w))
    return ran.groupBy(thread).agg(F.count(value).alias("turns"), F.avg(value).alias("mean"), F.min(value).alias("worst"), F.max_by(value, order).alias("last"), F.min("_running").alias("lowest_running"))


def written(df: DataFrame, path: str, by: list[str] | None = None, fmt: str = "parquet") -> DataFrame:
    """Store a report, partitioned if asked, and read it again; ``fmt`` is parquet, json (lines), csv or orc."""
    writer = df.write.format(fmt).option("header", True).mode("overwrite")
    (writer.partitionBy(*by) if by else writer).save(path)
    reader = df.sparkSession.read.format(fmt).option("header", True)
    return (reader if by else reader.schema(df.schema)).load(path)


def views(frames: dict[str, DataFrame]) -> None:
    for name, df in frames.items():
        df.createOrReplaceTempView(name)


def observed(df: DataFrame, name: str, **counters: Column) -> tuple[DataFrame, Observation]:
    """Counters that fill while ``df`` is consumed by whatever action comes; no pass of their own."""
    seen = Observation(name)
    return df.observe(seen, *(c.alias(n) for n, c in counters.items())), seen


class Timings:
    """Wall clock of a run by stage."""

    def __init__(self, clock: Callable[[], float] = time.monotonic) -> None:
        self.clock, self.rows = clock, []

    def stage(self, name: str, work: Callable[[], object]) -> object:
        begun = self.clock()
        out = work()
        self.rows.append((len(self.rows), name, self.clock() - begun))
        return out

    def table(self, spark: SparkSession) -> DataFrame:
        total = sum(s for *_, s in self.rows) or 1.0
        return spark.createDataFrame([(i, n, s, s / total) for i, n, s in self.rows], "position int, stage string, seconds double, share double")


def moment_diagnostics(df: DataFrame, value: str) -> DataFrame:
    """Skewness and excess kurtosis with the limits beyond which a sample of that size is not normal (two standard errors)."""
    v = F.col(value).cast("double")
    n = F.count(v)
    return df.agg(n.alias("n"), F.skewness(v).alias("skew"), F.kurtosis(v).alias("excess_kurtosis"), (2 * F.sqrt(6.0 / n)).alias("skew_limit"), (2 * F.sqrt(24.0 / n)).alias("kurtosis_limit"))


def distinct_prompts(df: DataFrame, text: str) -> DataFrame:
    """Exact and sketched numbers of distinct prompts, and whether the sketches come within a twentieth."""
    digest = F.xxhash64(text)
    made = df.agg(F.count_distinct(digest).alias("exact"), F.approx_count_distinct(digest, 0.01).alias("approximate"), F.hll_sketch_estimate(F.hll_sketch_agg(digest)).alias("sketched"))
    near = lambda c: F.abs(F.col(c) - F.col("exact")) <= 0.05 * F.col("exact") + 1
    return made.select("exact", near("approximate").alias("approximate_near"), near("sketched").alias("sketched_near"))
