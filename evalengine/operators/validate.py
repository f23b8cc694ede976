"""Simulations that validate intervals and tests: empirical coverage and type-I error."""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.functions.distributions import normal_cdf, normal_quantile, t_tail
from evalengine.operators import significance
from evalengine.sources.staging import staged


def _t_critical(n: int, level: float) -> float:
    lo, hi = 0.0, 100.0
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if t_tail(mid, n - 1) > 1 - level else (lo, mid)
    return (lo + hi) / 2


def numbered(population: DataFrame) -> tuple[DataFrame, int]:
    """The rows, staged, with ``place`` from 0 up without gaps, in the order of the partitions, and how many there are; a number a
    partition goes to the driver."""
    spark = population.sparkSession
    held = staged(population.withColumns({"_task": F.spark_partition_id(), "_row": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))}))
    sizes = sorted((r["_task"], r["count"]) for r in held.groupBy("_task").count().collect())
    if not sizes:
        raise ValueError("the population has no rows")
    ends = np.concatenate(([0], np.cumsum([n for _, n in sizes], dtype=np.int64))).tolist()
    begins = spark.createDataFrame([(k, begin) for (k, _), begin in zip(sizes, ends, strict=False)], "_task int, _begin long")
    return held.join(F.broadcast(begins), "_task").withColumn("place", F.col("_begin") + F.col("_row")).drop("_task", "_row", "_begin"), ends[-1]


def drawn(draws: DataFrame, population: tuple[DataFrame, int], *key: Column) -> DataFrame:
    """``draws`` with the columns of the row of the population that the digest of ``key`` gives each, drawn with replacement."""
    rows, n = population
    return draws.withColumn("place", F.pmod(F.xxhash64(*key), F.lit(n))).join(rows, "place").drop("place")


def coverage(spark: SparkSession, datasets: int = 1000, sizes: tuple[int, ...] = (50, 200, 1000), sigma: float = 0.5, iterations: int = 1000, level: float = 0.95, seed: int = 42, population: DataFrame | None = None) -> DataFrame:
    """Share of intervals for the mean that hold it, by method and size; a row a dataset.

    The samples are drawn from ``population`` (column ``value``; nulls go), of which the mean is known, or are lognormal(0, sigma) without one.
    """
    a = (1 - level) / 2
    if given := population is not None:
        rows = numbered(population.select(F.col("value").cast("double")).where("value IS NOT NULL"))
    truth = rows[0].agg(F.avg("value")).first()[0] if given else float(np.exp(sigma**2 / 2))
    critical = {n: _t_critical(n, level) for n in sizes}
    za, zb = normal_quantile(a), normal_quantile(1 - a)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for row, (i, n) in enumerate(zip(b["dataset"], b["n"], strict=True)):
                rng = np.random.default_rng([seed, int(i), int(n)])
                x = np.asarray(b["sample"].iloc[row]) if given else rng.lognormal(0, sigma, n)
                reps = np.sort(np.concatenate([x[rng.integers(0, n, (min(100, iterations - k), n))].mean(axis=1) for k in range(0, iterations, 100)]))
                mean = x.mean()
                half = critical[n] * x.std(ddof=1) / np.sqrt(n)
                share = min(max((reps < mean).mean(), 0.5 / iterations), 1 - 0.5 / iterations)
                z0, u = normal_quantile(share), x - mean
                acc = (u**3).sum() / (6 * (u**2).sum() ** 1.5)
                q = [normal_cdf(z0 + (z0 + z) / (1 - acc * (z0 + z))) for z in (za, zb)]
                found = {"t": (mean - half, mean + half), "percentile": tuple(np.quantile(reps, [a, 1 - a])), "bca": tuple(np.quantile(reps, q))}
                out += [(int(n), m, float(lo <= truth <= hi)) for m, (lo, hi) in found.items()]
            yield pd.DataFrame(out, columns=["n", "method", "hit"])

    grid = spark.range(datasets).withColumn("n", F.explode(F.array(*map(F.lit, sizes)))).select(F.col("id").alias("dataset"), "n").repartition(2 * spark.sparkContext.defaultParallelism, "dataset")
    if given:
        draws = grid.withColumn("k", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
        samples = drawn(draws, rows, F.lit(seed), F.col("dataset"), F.col("n"), F.col("k")).groupBy("dataset", "n").agg(F.sort_array(F.collect_list(F.struct("k", "value"))).alias("x"))
        grid = samples.select("dataset", "n", F.col("x.value").alias("sample"))
    return grid.mapInPandas(run, "n int, method string, hit double").groupBy("n", "method").agg(F.avg("hit").alias("coverage"), F.count("*").alias("datasets"))


def type_one(spark: SparkSession, comparisons: int = 10_000, n: int = 100, alpha: float = 0.05, seed: int = 7, population: DataFrame | None = None) -> DataFrame:
    """Share of rejections where both sides come from one distribution, by test.

    The comparisons are groups of pairs, and the tests are those of ``significance``, by group. Both sides are drawn from ``population``
    (columns ``value`` and ``right``, a boolean; rows with a null go), or are normal and multinomial numbers without one.
    """
    grid = spark.range(0, comparisons, 1, 2 * spark.sparkContext.defaultParallelism)

    def pairs(draw: Callable[[np.random.Generator], tuple[np.ndarray, np.ndarray]], stream: int) -> DataFrame:
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                for i in b["id"]:
                    x, y = draw(np.random.default_rng([seed, stream, int(i)]))
                    yield pd.DataFrame({"comparison": np.full(len(x), i), "a": x, "b": y})

        return grid.mapInPandas(run, "comparison long, a double, b double")

    def answers(rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        u = rng.random(5 * n)
        return (u < 0.2).astype(float), ((u >= 0.2) & (u < 0.4)).astype(float)

    by = ["comparison"]
    if population is None:
        values, marks = pairs(lambda rng: (rng.standard_normal(n), rng.standard_normal(n)), 0), pairs(answers, 1)
    else:
        rows, size = numbered(population.select(F.col("value").cast("double"), F.col("right").cast("double")).where("value IS NOT NULL AND right IS NOT NULL"))

        def two(column: str, count: int, stream: int) -> DataFrame:
            out = grid.select(F.col("id").alias("comparison"), F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("k"))
            for side, name in enumerate("ab"):
                out = drawn(out, (rows.select("place", F.col(column).alias(name)), size), F.lit(seed), F.lit(stream), F.lit(side), F.col("comparison"), F.col("k"))
            return staged(out.drop("k"))

        values, marks = two("value", n, 0), two("right", 5 * n, 1)
    found = {"paired_t": significance.paired_t(values, by), "signed_rank": significance.signed_rank(values, by=by), "discordant": significance.discordant(marks, by=by)}
    seen = functools.reduce(DataFrame.unionByName, (r.select(F.lit(test).alias("test"), (F.col("p_value") < alpha).cast("double").alias("rejected")) for test, r in found.items()))
    return seen.groupBy("test").agg(F.avg("rejected").alias("rate"), F.count("*").alias("comparisons"))
