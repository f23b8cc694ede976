"""Confidence intervals: closed forms from one aggregate, and bootstraps by engines that move little data.

``exact`` draws rows by digest (a join of n*B rows; small inputs), ``histogram`` draws a multinomial over distinct
values (one small group), ``split`` deals each replicate's draws over partitions and draws inside them, and
``poisson`` gives each row an independent Poisson(1) weight by digest. The last two move P*B partial sums only.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F

from evalengine.functions.distributions import normal_quantile, phi, phi_inv, poisson_one, t_quantile, uniform

ENGINES = ("exact", "histogram", "split", "poisson")


def moments(df: DataFrame, value: str, by: list[str] | None = None) -> DataFrame:
    """n, missing, mean, sd and power sums about the mean's pivot, in one pass."""
    v = F.col(value).cast("double")
    return df.groupBy(*(by or [])).agg(
        F.count(v).alias("n"), F.count_if(v.isNull()).alias("n_missing"), F.avg(v).alias("mean"), F.stddev_samp(v).alias("sd"), F.min(v).alias("low"), F.max(v).alias("high"),
        F.sum(v).alias("s1"), F.sum(v * v).alias("s2"), F.sum(v * v * v).alias("s3"),
    )


def moments_wide(df: DataFrame, values: list[str]) -> dict[str, Row]:
    """``moments`` of several columns from one aggregate over one scan, by column."""
    empty = df.sparkSession.createDataFrame([], "v double")
    names = moments(empty, "v").columns
    v = lambda c: F.col(c).cast("double")
    made = lambda c: (F.count(v(c)), F.count_if(v(c).isNull()), F.avg(v(c)), F.stddev_samp(v(c)), F.min(v(c)), F.max(v(c)), F.sum(v(c)), F.sum(v(c) * v(c)), F.sum(v(c) * v(c) * v(c)))
    row = df.agg(*(x.alias(f"{i}_{n}") for i, c in enumerate(values) for n, x in zip(names, made(c), strict=True))).first()
    return {c: Row(**{n: row[f"{i}_{n}"] for n in names}) for i, c in enumerate(values)}


def t_mean(df: DataFrame, value: str, level: float = 0.95, by: list[str] | None = None) -> DataFrame:
    """Mean with x +- t s / sqrt(n). No rows: null; one row: the point."""
    m = moments(df, value, by)
    half = F.when(F.col("n") > 1, t_quantile((1 + level) / 2, (F.col("n") - 1).cast("double")) * F.col("sd") / F.sqrt(F.col("n"))).when(F.col("n") == 1, 0.0)
    return m.select(*(by or []), "n", F.col("mean").alias("value"), (F.col("mean") - half).alias("ci_lo"), (F.col("mean") + half).alias("ci_hi"))


def wilson(successes: Column, n: Column, level: float = 0.95) -> tuple[Column, Column]:
    z = normal_quantile((1 + level) / 2)
    p = F.try_divide(successes.cast("double"), n)
    centre, scale = (p + z * z / (2 * n)), 1 + z * z / n
    half = z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))
    low = F.when(successes == 0, F.when(n > 0, 0.0)).otherwise((centre - half) / scale)
    high = F.when(successes == n, F.when(n > 0, 1.0)).otherwise((centre + half) / scale)
    return low, high


def wald(successes: Column, n: Column, level: float = 0.95) -> tuple[Column, Column]:
    z = normal_quantile((1 + level) / 2)
    p = F.try_divide(successes.cast("double"), n)
    half = z * F.sqrt(p * (1 - p) / n)
    return p - half, p + half


def proportion(df: DataFrame, value: str, method=wilson, level: float = 0.95, by: list[str] | None = None) -> DataFrame:
    """Share of ones with its interval, by groups if asked."""
    m = df.groupBy(*(by or [])).agg(F.count(value).alias("n"), F.count_if(F.col(value) > 0).alias("k"))
    low, high = method(F.col("k"), F.col("n"), level)
    return m.select(*(by or []), "n", F.try_divide(F.col("k").cast("double"), "n").alias("value"), low.alias("ci_lo"), high.alias("ci_hi"))


# Replicates: (replicate, estimate) of the mean.


def _indexed(df: DataFrame, value: str, key: str) -> DataFrame:
    """A dense row number without a global window: per-range counts, then offsets."""
    ranged = df.select(F.col(key).alias("_k"), F.col(value).cast("double").alias("v")).where("v IS NOT NULL").repartitionByRange("_k").sortWithinPartitions("_k", "v")
    numbered = ranged.select("v", F.spark_partition_id().alias("p"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("r"))
    from pyspark.sql import Window

    offsets = numbered.groupBy("p").agg(F.count("*").alias("c")).select("p", (F.sum("c").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1))).alias("o"))
    return numbered.join(F.broadcast(offsets), "p").select((F.col("r") + F.coalesce("o", F.lit(0))).alias("i"), "v")


#: Upper ends of the steps of a Poisson(1) law on the unit interval, in 32 bits; beyond the last it is not told apart.
_STEPS = np.minimum(np.cumsum([math.exp(-1) / math.factorial(k) for k in range(13)]) * 2.0**32, 2.0**32 - 1).astype(np.uint64)


def poisson_weights(salts: np.ndarray, iterations: int, seed: int) -> np.ndarray:
    """A matrix of Poisson(1) weights, a row for each salt and a column for each replicate: each from a hashed counter of
    both, so that a row's weights do not depend on where it lies."""
    with np.errstate(over="ignore"):
        h = salts[:, None] + np.uint64(seed) * np.uint64(0xD1B54A32D192ED03) + np.arange(1, iterations + 1, dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            h = (h ^ (h >> np.uint64(shift))) * np.uint64(factor)
    return np.searchsorted(_STEPS, (h ^ (h >> np.uint64(31))) >> np.uint64(32), side="right").astype(np.float64)


def replicates(df: DataFrame, value: str, iterations: int = 1000, seed: int = 42, engine: str = "auto", key: str | None = None) -> DataFrame:
    """``replicate``, ``estimate``: the mean of each resample. ``key`` names a row id for the digest engines."""
    v = df.select(*([key] if key else []), F.col(value).cast("double").alias("v")).where("v IS NOT NULL")
    if engine == "auto":
        size = v.agg(F.count("*").alias("n"), F.approx_count_distinct("v").alias("d")).first()
        engine = "histogram" if size.d <= 50_000 else "split"
    if engine == "exact":
        rows = _indexed(df, value, key or value)
        n = rows.count()
        draws = df.sparkSession.range(iterations).select(F.col("id").cast("int").alias("replicate")).crossJoin(df.sparkSession.range(n).select(F.col("id").alias("j")))
        drawn = draws.select("replicate", F.floor(uniform(F.lit(seed), "replicate", "j") * n).cast("long").alias("i"))
        return drawn.join(rows, "i").groupBy("replicate").agg(F.avg("v").alias("estimate"))
    if engine == "poisson":
        salt = F.xxhash64(*(key,)) if key else F.xxhash64("v", F.spark_partition_id(), F.monotonically_increasing_id())

        def weigh(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total, weight = np.zeros(iterations), np.zeros(iterations)
            for b in batches:
                x, s = b["v"].to_numpy(), b["s"].to_numpy().astype(np.uint64)
                for k in range(0, len(x), 4096):
                    w = poisson_weights(s[k : k + 4096], iterations, seed)
                    total += x[k : k + 4096] @ w
                    weight += w.sum(axis=0)
            yield pd.DataFrame({"replicate": np.arange(iterations, dtype=np.int32), "t": total, "w": weight})

        parts = v.withColumn("s", salt).select("v", "s").mapInPandas(weigh, "replicate int, t double, w double")
        return parts.groupBy("replicate").agg((F.try_divide(F.sum("t"), F.sum("w"))).alias("estimate"))
    if engine == "histogram":
        counts = v.groupBy("v").count()

        def draw(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values("v")
            x, c = pdf["v"].to_numpy(), pdf["count"].to_numpy()
            drawn = np.random.default_rng(seed).multinomial(c.sum(), c / c.sum(), iterations)
            return pd.DataFrame({"replicate": np.arange(iterations, dtype=np.int32), "estimate": drawn @ x / c.sum()})

        return counts.groupBy(F.lit(1).alias("one")).applyInPandas(draw, "replicate int, estimate double")
    if engine != "split":
        raise ValueError(f"unknown engine {engine}")
    placed = v.repartitionByRange(*([key] if key else ["v"])).sortWithinPartitions(*([key] if key else ["v"])).select("v")
    sizes = {r.p: r.n for r in placed.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n")).collect()}
    order, n = sorted(sizes), sum(sizes.values())
    dealt = np.random.default_rng(seed).multinomial(n, [sizes[p] / n for p in order], iterations) if n else np.zeros((iterations, 0), int)
    shares = df.sparkSession.sparkContext.broadcast({p: dealt[:, k] for k, p in enumerate(order)})

    def local(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        p = TaskContext.get().partitionId()
        x = np.concatenate([np.zeros(0), *(b["v"].to_numpy() for b in batches)])
        rng = np.random.default_rng([seed, p])
        sums = [x[rng.integers(0, len(x), int(k))].sum() for k in shares.value[p]] if len(x) else np.zeros(iterations)
        yield pd.DataFrame({"replicate": np.arange(iterations, dtype=np.int32), "t": sums})

    return placed.mapInPandas(local, "replicate int, t double").groupBy("replicate").agg((F.sum("t") / max(n, 1)).alias("estimate"))


def weighted_replicates(df: DataFrame, stats: list[str], key: str, iterations: int, seed: int) -> DataFrame:
    """``replicate`` and the sums of each statistic under Poisson(1) digest weights: additive, so also for streams."""
    weights = df.select(key, *stats).withColumn("replicate", F.explode(F.sequence(F.lit(0), F.lit(iterations - 1)))).withColumn("w", poisson_one(uniform(F.lit(seed), "replicate", key)))
    return weights.groupBy("replicate").agg(*(F.sum(F.col("w") * F.col(s)).alias(s) for s in stats))


def percentile_complex(df: DataFrame, stats: list[str], finish: Column, key: str, iterations: int = 1000, level: float = 0.95, seed: int = 42) -> DataFrame:
    """An interval for any function ``finish`` of summed statistics (such as corpus BLEU)."""
    return percentile_of(weighted_replicates(df, stats, key, iterations, seed).select("replicate", finish.alias("estimate")), level)


def percentile_of(reps: DataFrame, level: float = 0.95) -> DataFrame:
    a = (1 - level) / 2
    return reps.agg(F.percentile("estimate", a).alias("ci_lo"), F.percentile("estimate", 1 - a).alias("ci_hi"))


def quantile_at(sorted_values: Column, q: Column) -> Column:
    """Linear interpolation at position (B-1) q of a sorted array; q is data."""
    at = q * (F.size(sorted_values) - 1)
    low = F.floor(at).cast("int")
    x, y = F.get(sorted_values, low), F.coalesce(F.get(sorted_values, low + 1), F.get(sorted_values, low))
    return x + (y - x) * (at - low)


def acceleration(m: DataFrame) -> DataFrame:
    """Jackknife acceleration of a mean from its power sums: M3 / (6 M2^1.5)."""
    n, mean = F.col("n"), F.col("mean")
    m2 = F.col("s2") - n * mean * mean
    m3 = F.col("s3") - 3 * mean * F.col("s2") + 2 * n * mean * mean * mean
    return m.withColumn("acceleration", F.when(m2 > 0, m3 / (6 * F.pow(m2, 1.5))).otherwise(0.0))


def acceleration_complex(df: DataFrame, stats: list[str], finish: Column, blocks: int | None = None, key: str | None = None) -> DataFrame:
    """Jackknife acceleration of ``finish``: the totals without each row (or each block) in turn."""
    parts = df.select(*stats, F.pmod(F.xxhash64(key), F.lit(blocks)).alias("_b")).groupBy("_b").agg(*(F.sum(s).alias(s) for s in stats)) if blocks else df.select(*stats)
    totals = parts.agg(*(F.sum(s).alias(f"_t_{s}") for s in stats))
    left = parts.crossJoin(F.broadcast(totals)).select(*((F.col(f"_t_{s}") - F.col(s)).alias(s) for s in stats)).select(finish.alias("x"))
    m = moments(left, "x")
    return acceleration(m).select((-F.col("acceleration")).alias("acceleration"))


def bca_of(reps: DataFrame, point: DataFrame, level: float = 0.95) -> DataFrame:
    """BCa from replicates and one row with ``mean`` and ``acceleration``. Ties count half; shares stay off 0 and 1."""
    gathered = reps.agg(F.sort_array(F.collect_list("estimate")).alias("r"))
    row = gathered.crossJoin(F.broadcast(point))
    b = F.size("r")
    below = F.size(F.filter("r", lambda x: x < F.col("mean"))) + 0.5 * F.size(F.filter("r", lambda x: x == F.col("mean")))
    share = F.greatest(0.5 / b, F.least(1 - 0.5 / b, below / b))
    row = row.withColumn("z0", phi_inv(share))

    def bound(q: float) -> Column:
        z = F.col("z0") + normal_quantile(q)
        return quantile_at(F.col("r"), phi(F.col("z0") + z / (1 - F.col("acceleration") * z)))

    a = (1 - level) / 2
    return row.select(F.col("mean").alias("value"), bound(a).alias("ci_lo"), bound(1 - a).alias("ci_hi"), "n", "z0", "acceleration")


def bca(df: DataFrame, value: str, iterations: int = 1000, level: float = 0.95, seed: int = 42, engine: str = "auto", key: str | None = None) -> DataFrame:
    return bca_of(replicates(df, value, iterations, seed, engine, key), acceleration(moments(df, value)), level)


def percentile(df: DataFrame, value: str, iterations: int = 1000, level: float = 0.95, seed: int = 42, engine: str = "auto", key: str | None = None) -> DataFrame:
    return percentile_of(replicates(df, value, iterations, seed, engine, key), level).crossJoin(moments(df, value).select(F.col("mean").alias("value"), "n"))


def choose(kind: str, n: int, skew: float = 0.0, requested: str = "auto", large: int = 1000) -> tuple[str, str]:
    """(method, reason)."""
    if requested != "auto":
        if requested in ("wilson", "wald") and kind != "binary":
            raise ValueError("wilson and wald are for binary metrics")
        return requested, "requested"
    if kind == "binary":
        return "wilson", "a proportion"
    if kind == "complex":
        return "percentile", "no closed form"
    if n >= large and abs(skew) < math.sqrt(n) / 10:
        return "t", "a mean of many"
    return "bca", "few or skewed values"
