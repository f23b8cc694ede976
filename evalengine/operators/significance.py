"""Paired tests, effect sizes, test choice. Inputs are rows (a, b); outputs one row of plain aggregates."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evalengine.functions.distributions import normal_cdf, phi, t_tail, t_two_sided, uniform


def paired_t(df: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Paired t test of the mean difference, by groups if asked; all differences zero gives p = 1."""
    d = F.col("a").cast("double") - F.col("b").cast("double")
    m = df.groupBy(*(by or [])).agg(F.count(d).alias("n"), F.avg(d).alias("mean_diff"), F.stddev_samp(d).alias("sd"))
    t = F.when(F.col("sd") > 0, F.col("mean_diff") / (F.col("sd") / F.sqrt("n")))
    same = (F.col("sd") == 0) & (F.col("mean_diff") == 0)
    return m.select(*(by or []), "n", "mean_diff",F.when(same, 0.0).otherwise(t).alias("statistic"), F.when(same, 1.0).otherwise(t_two_sided(t, (F.col("n") - 1).cast("double"))).alias("p_value"))


def table2(df: DataFrame, by: list[str] | None = None) -> DataFrame:
    a, b = F.col("a") > 0, F.col("b") > 0
    return df.groupBy(*(by or [])).agg(F.count_if(a & b).alias("both"), F.count_if(a & ~b).alias("only_a"), F.count_if(~a & b).alias("only_b"), F.count_if(~a & ~b).alias("neither"))


def exact_binomial(b: Column, c: Column, mid_p: bool = False) -> Column:
    """Two-sided P under fair splits of b + c discordant pairs: a fold of min(b, c) steps on logarithms of the terms.

    ``mid_p`` counts the observed split half.
    """
    n, low = (b + c).cast("double"), F.least(b, c)
    zero = F.struct((n * -math.log(2)).alias("term"), F.lit(0.0).alias("tail"))

    def step(s: Column, k: Column) -> Column:
        term = s["term"] + F.when(k == 0, 0.0).otherwise(F.log((n - k + 1) / F.greatest(k, F.lit(1))))
        return F.struct(term.alias("term"), (s["tail"] + F.exp(term)).alias("tail"))

    def p(s: Column) -> Column:
        return F.least(F.lit(1.0), 2 * s["tail"] - (F.exp(s["term"]) if mid_p else F.lit(0.0)))

    return F.aggregate(F.sequence(F.lit(0).cast("long"), low.cast("long")), zero, step, p)


def discordant(df: DataFrame, correction: bool = False, exact_below: int | None = 10, mid_p: bool = False, by: list[str] | None = None) -> DataFrame:
    """Discordant pairs: chi-squared with one degree of freedom, the exact binomial below ``exact_below`` pairs (None: always)."""
    t = table2(df, by)
    b, c = F.col("only_a"), F.col("only_b")
    gap = F.abs(b - c) - (1 if correction else 0)
    chi = F.try_divide((F.greatest(gap, F.lit(0)) * F.greatest(gap, F.lit(0))).cast("double"), b + c)
    few = F.lit(True) if exact_below is None else b + c < exact_below
    exact = exact_binomial(F.when(few, b).otherwise(0), F.when(few, c).otherwise(0), mid_p)
    return t.select(*(by or []), "only_a", "only_b", F.when(few, F.lit("exact")).otherwise("chi2").alias("branch"), chi.alias("statistic"), F.when(few, exact).otherwise(2 * (1 - phi(F.sqrt(chi)))).alias("p_value"))


def signed_rank(df: DataFrame, correction: bool = True, by: list[str] | None = None) -> DataFrame:
    """Wilcoxon signed rank with average ranks and tie correction, normal tail.

    Works on the counts of distinct absolute differences, so rows are only aggregated, never ranked. ``by`` is for
    many groups of bounded size: each group's distinct differences are ranked in one window. A group without a
    difference other than zero has no row.
    """
    d, by = F.round(F.col("a").cast("double") - F.col("b").cast("double"), 9), by or []
    counts = df.select(*by, d.alias("d")).where("d IS NOT NULL AND d <> 0").groupBy(*by, F.abs("d").alias("m")).agg(F.count_if(F.col("d") > 0).alias("up"), F.count("*").alias("t"))
    if by:
        below = F.sum("t").over(Window.partitionBy(*by).orderBy("m").rowsBetween(Window.unboundedPreceding, Window.currentRow))
        ranked = counts.withColumn("rank", below - (F.col("t") - 1) / 2.0)
    else:
        ranked = ranks(counts, "m", "t")
    n = F.sum("t").cast("double")
    s = ranked.groupBy(*by).agg(
        F.coalesce(F.sum(F.col("up") * F.col("rank")), F.lit(0.0)).alias("w_plus"), F.coalesce(F.sum((F.col("t") - F.col("up")) * F.col("rank")), F.lit(0.0)).alias("w_minus"),
        F.coalesce(n, F.lit(0.0)).alias("n"), F.coalesce(F.sum(F.col("t").cast("double") * F.col("t") * F.col("t") - F.col("t")), F.lit(0.0)).alias("ties"),
    )
    k = F.col("n")
    var = k * (k + 1) * (2 * k + 1) / 24 - F.col("ties") / 48
    gap = F.greatest(F.abs(F.col("w_plus") - k * (k + 1) / 4) - (0.5 if correction else 0.0), F.lit(0.0))
    z = F.when(var > 0, gap / F.sqrt(var)).otherwise(0.0)
    return s.select(*by, k.cast("long").alias("n"), "w_plus","w_minus", z.alias("statistic"), F.when(k == 0, 1.0).otherwise(2 * (1 - phi(z))).alias("p_value"))


def ranks(counts: DataFrame, value: str, weight: str, parts: int = 64) -> DataFrame:
    """Average rank of each distinct value: a running sum inside value ranges, plus the broadcast totals of the ranges below."""
    edges = counts.agg(F.percentile_approx(value, [i / parts for i in range(1, parts)], 10_000).alias("e")).first()
    bounds = sorted(set(edges.e or [])) if edges else []
    where = F.size(F.filter(F.array(*map(F.lit, bounds)), lambda b: b < F.col(value))) if bounds else F.lit(0)
    held = counts.withColumn("_part", where)
    totals = held.groupBy("_part").agg(F.sum(weight).alias("_w"))
    offset = totals.select("_part", F.coalesce(F.sum("_w").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_below"))
    run = F.sum(weight).over(Window.partitionBy("_part").orderBy(value).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return held.withColumn("_run", run).join(F.broadcast(offset), "_part").withColumn("rank", F.col("_below") + F.col("_run") - (F.col(weight) - 1) / 2.0).drop("_part", "_run", "_below")


def permutation(df: DataFrame, key: str, iterations: int = 1000, seed: int = 42, counting: str = "plus_one") -> DataFrame:
    """Label swaps by digest: the share of swapped mean differences at least as far from 0 as the observed one."""
    rows = df.select(key, (F.col("a").cast("double") - F.col("b").cast("double")).alias("d")).where("d IS NOT NULL")
    observed = rows.agg(F.sum("d").alias("total"), F.count("*").alias("n"))
    sign = F.when(uniform(F.lit(seed), "replicate", key) < 0.5, -1.0).otherwise(1.0)
    swapped = rows.withColumn("replicate", F.explode(F.sequence(F.lit(0), F.lit(iterations - 1)))).groupBy("replicate").agg(F.sum(sign * F.col("d")).alias("s"))
    extreme = F.count_if(F.abs("s") >= F.abs("total") - 1e-9)
    p = (extreme + 1) / (F.count("*") + 1) if counting == "plus_one" else extreme / F.count("*")
    return swapped.crossJoin(F.broadcast(observed)).groupBy("total", "n").agg(p.alias("p_value"), extreme.alias("extreme")).select("n", (F.col("total") / F.col("n")).alias("statistic"), "extreme", "p_value")


def permutation_fast(df: DataFrame, iterations: int = 1000, seed: int = 42) -> DataFrame:
    """The same law from counts of distinct differences: one binomial draw for each value and replicate."""
    counts = df.select(F.round(F.abs(F.col("a").cast("double") - F.col("b").cast("double")), 9).alias("m"), F.signum(F.col("a").cast("double") - F.col("b").cast("double")).alias("s")).groupBy("m").agg(F.count("*").alias("t"), F.sum("s").alias("net"))

    def draw(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("m")
        m, t = pdf["m"].to_numpy(), pdf["t"].to_numpy()
        up = np.random.default_rng(seed).binomial(t, 0.5, (iterations, len(t)))
        s, total = (2 * up - t) @ m, float((pdf["net"] * pdf["m"]).sum())
        return pd.DataFrame({"n": [int(t.sum())], "statistic": [total / t.sum()], "p_value": [(1 + (np.abs(s) >= abs(total) - 1e-9).sum()) / (iterations + 1)]})

    return counts.groupBy(F.lit(1).alias("one")).applyInPandas(draw, "n long, statistic double, p_value double")


# Effects.


def _sides(df: DataFrame) -> DataFrame:
    a, b = F.col("a").cast("double"), F.col("b").cast("double")
    return df.agg(F.count(a).alias("n1"), F.count(b).alias("n2"), F.avg(a).alias("x1"), F.avg(b).alias("x2"), F.var_samp(a).alias("v1"), F.var_samp(b).alias("v2"), F.stddev_samp(a - b).alias("sd_d"))


def band(effect: Column, cuts: tuple[float, float, float] = (0.2, 0.5, 0.8)) -> Column:
    e = F.abs(effect)
    return F.when(e < cuts[0], "negligible").when(e < cuts[1], "small").when(e < cuts[2], "medium").otherwise("large")


def cohen_d(df: DataFrame, variant: str = "pooled") -> DataFrame:
    s = _sides(df)
    pooled = F.sqrt(((F.col("n1") - 1) * F.col("v1") + (F.col("n2") - 1) * F.col("v2")) / (F.col("n1") + F.col("n2") - 2))
    d = F.try_divide(F.col("x1") - F.col("x2"), pooled if variant == "pooled" else F.col("sd_d"))
    return s.select((F.col("n1") + F.col("n2") - 2).alias("df"), d.alias("effect"), band(d).alias("band"))


def hedges_g(df: DataFrame, exact: bool = False) -> DataFrame:
    d = cohen_d(df)
    if exact:
        nu = float(d.first()["df"])
        factor: Column = F.lit(math.exp(math.lgamma(nu / 2) - math.lgamma((nu - 1) / 2)) / math.sqrt(nu / 2))
    else:
        factor = 1 - 3 / (4 * F.col("df") - 1)
    return d.select("df", (F.col("effect") * factor).alias("effect"))


def odds_ratio(df: DataFrame, matched: bool = False) -> DataFrame:
    """Odds of success of A over B; one half is added to every cell where one is empty."""
    t = table2(df)
    if matched:
        b, c = F.col("only_a"), F.col("only_b")
        add = F.when((b == 0) | (c == 0), 0.5).otherwise(0.0)
        return t.select(((b + add) / (c + add)).alias("effect"))
    wins_a, wins_b = F.col("both") + F.col("only_a"), F.col("both") + F.col("only_b")
    n = F.col("both") + F.col("only_a") + F.col("only_b") + F.col("neither")
    add = F.when((wins_a == 0) | (wins_b == 0) | (wins_a == n) | (wins_b == n), 0.5).otherwise(0.0)
    return t.select((((wins_a + add) / (n - wins_a + add)) / ((wins_b + add) / (n - wins_b + add))).alias("effect"))


# Choice.


def recommend(kind: str, n: int, normal: bool | None = None, discordant_pairs: int | None = None) -> tuple[str, str]:
    """(test, reason) for a metric kind, sample size and normality."""
    if kind == "binary":
        few = discordant_pairs is not None and discordant_pairs < 10
        return ("discordant_exact" if few else "discordant_chi2"), "binary metric" + (", under 10 discordant pairs" if few else "")
    if kind == "ordinal":
        return "signed_rank", "ordinal metric"
    if kind == "complex":
        return "permutation", "no analytical test"
    if normal and n > 30:
        return "paired_t", "normal differences, more than 30"
    return "signed_rank", "differences not normal" if not normal else "30 differences or fewer"


def shapiro_wilk(x: np.ndarray) -> tuple[float, float]:
    """W and p by Royston's approximation, 3 <= n <= 5000."""
    x = np.sort(np.asarray(x, float))
    n = len(x)
    if n < 3 or x[0] == x[-1]:
        return 1.0, 1.0
    from evalengine.functions.distributions import normal_quantile

    half = n // 2
    m = np.array([normal_quantile((i - 0.375) / (n + 0.25)) for i in range(n - half + 1, n + 1)])[::-1]
    ssq = 2 * (m**2).sum()
    u, r = 1 / math.sqrt(n), m / math.sqrt(ssq)
    a = r.copy()
    # Royston's polynomials for the largest weights and for the distribution of log(1 - W).
    c1, c2 = (0.221157, -0.147981, -2.07119, 4.434685, -2.706056), (0.042981, -0.293762, -1.752461, 5.682633, -3.582633)
    poly = lambda c, v: sum(k * v ** (i + 1) for i, k in enumerate(c))
    if n == 3:
        a[0] = math.sqrt(0.5)
    else:
        a[0] = r[0] + poly(c1, u)
        if n > 5:
            a[1] = r[1] + poly(c2, u)
            scale = (ssq - 2 * m[0] ** 2 - 2 * m[1] ** 2) / (1 - 2 * a[0] ** 2 - 2 * a[1] ** 2)
            a[2:] = m[2:] / math.sqrt(scale)
        else:
            scale = (ssq - 2 * m[0] ** 2) / (1 - 2 * a[0] ** 2)
            a[1:] = m[1:] / math.sqrt(scale)
    w = min(1.0, float((a * (x[::-1][:half] - x[:half])).sum() ** 2 / ((x - x.mean()) ** 2).sum()))
    if n == 3:
        return w, max(0.0, 6 / math.pi * (math.asin(math.sqrt(w)) - math.asin(math.sqrt(0.75))))
    if n <= 11:
        g = -2.273 + 0.459 * n
        z = (-math.log(g - math.log(max(1e-300, 1 - w))) - (0.544 - 0.39978 * n + 0.025054 * n**2 - 0.0006714 * n**3)) / math.exp(1.3822 - 0.77857 * n + 0.062767 * n**2 - 0.0020322 * n**3)
    else:
        k = math.log(n)
        z = (math.log(max(1e-300, 1 - w)) - (-1.5861 - 0.31082 * k - 0.083751 * k**2 + 0.0038915 * k**3)) / math.exp(-0.4803 - 0.082676 * k + 0.0030302 * k**2)
    return w, 1 - normal_cdf(z)


def normality(df: DataFrame, value: str, cap: int = 5000) -> DataFrame:
    """Shapiro-Wilk of at most ``cap`` values (the test's own limit is 5,000).

    The sample depends on the values alone, not on how rows are dealt: a value that occurs c times draws the lowest of
    c uniform numbers in order, from a generator of its own, and the lowest numbers of all values win.
    """
    counts = df.select(F.col(value).cast("double").alias("v")).where("v IS NOT NULL").groupBy("v").agg(F.count("*").alias("c")).withColumn("s", F.xxhash64("v"))

    def draw(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for v, c, s in zip(b["v"], b["c"], b["s"], strict=True):
                k = min(int(c), cap)
                # Successive minima of c exponentials, which order as the minima of c uniforms do.
                u = np.cumsum(np.random.default_rng(int(s) & (2**63 - 1)).exponential(size=k) / (c - np.arange(k)))
                yield pd.DataFrame({"v": np.full(k, v), "u": u})

    kept = counts.mapInPandas(draw, "v double, u double").orderBy("u", "v").limit(cap)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        w, p = shapiro_wilk(pdf["v"].to_numpy())
        return pd.DataFrame({"n": [len(pdf)], "statistic": [w], "p_value": [p]})

    return kept.groupBy(F.lit(1).alias("one")).applyInPandas(run, "n long, statistic double, p_value double")


def exact_t(t: float, n: int) -> float:
    return t_tail(t, n - 1)


def exact_signed_rank(d: list[float]) -> float:
    """Two-sided exact P of untied non-zero differences, by counts of rank sums."""
    x = sorted((abs(v), v > 0) for v in d if v)
    n = len(x)
    w = sum(i + 1 for i, (_, up) in enumerate(x) if up)
    ways = np.zeros(n * (n + 1) // 2 + 1)
    ways[0] = 1
    for r in range(1, n + 1):
        ways[r:] += ways[:-r].copy()
    low = min(w, n * (n + 1) // 2 - w)
    return float(min(1.0, 2 * ways[: low + 1].sum() / 2**n)) if n else 1.0


def compare(df: DataFrame, kind: str, metric: str = "metric", key: str | None = None, alpha: float = 0.05) -> DataFrame:
    """Choose the test, run it, and give the effect beside it: one row."""
    n = df.count()
    if kind == "binary":
        r = discordant(df).first()
        name, why = recommend("binary", n, discordant_pairs=r.only_a + r.only_b)
        effect = ("odds_ratio", odds_ratio(df).first().effect)
    else:
        normal = None
        if kind == "continuous":
            normal = normality(df.select((F.col("a") - F.col("b")).alias("d")), "d").first().p_value > alpha
        name, why = recommend(kind, n, normal)
        r = (paired_t(df) if name == "paired_t" else signed_rank(df) if name == "signed_rank" else permutation_fast(df)).first()
        effect = ("cohen_d", cohen_d(df).first().effect)
    row = (metric, name, r.statistic, r.p_value, n, *effect, why)
    return df.sparkSession.createDataFrame([row], "metric string, test string, statistic double, p_value double, n long, effect_name string, effect double, reason string").withColumn("effect_band", band(F.col("effect")))


def adjusted(rows: DataFrame, p: str = "p_value") -> DataFrame:
    """Holm and Benjamini-Hochberg adjusted p values of a small table of comparisons."""
    w = Window.orderBy(p)
    n = rows.count()
    r = rows.withColumn("_i", F.row_number().over(w))
    holm = F.least(F.lit(1.0), F.max(F.col(p) * (n - F.col("_i") + 1)).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    bh = F.least(F.lit(1.0), F.min(F.col(p) * n / F.col("_i")).over(w.rowsBetween(0, Window.unboundedFollowing)))
    return r.withColumns({"p_holm": holm, "p_bh": bh}).drop("_i")
