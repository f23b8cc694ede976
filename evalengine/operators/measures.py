"""Cost and performance measures over call logs and price lists."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

PRICES = "provider_id string, model_id string, usd_per_m_prompt decimal(18,6), usd_per_m_completion decimal(18,6)"


def prices(spark: SparkSession, rows: list[tuple[str, str, str, str]]) -> DataFrame:
    """A price list from literal rows; its size is that of the list."""
    typed = spark.createDataFrame(rows, "provider_id string, model_id string, i string, o string")
    return typed.select("provider_id", "model_id", F.col("i").cast("decimal(18,6)").alias("usd_per_m_prompt"), F.col("o").cast("decimal(18,6)").alias("usd_per_m_completion"))


def cost(calls: DataFrame, price_list: DataFrame) -> DataFrame:
    """Money by provider and model: tokens are summed before the price list is joined."""
    sums = calls.groupBy("provider_id", "model_id").agg(F.sum("prompt_tokens").alias("p"), F.sum("completion_tokens").alias("c"), F.count("*").alias("calls"))
    # Whole tokens by a price a million are micro-dollars; rounded once, half up, and exact otherwise.
    money = lambda tokens, price: (F.round(F.col(tokens).cast("decimal(18,0)") * F.col(price), 0).cast("decimal(24,0)") * F.lit("0.000001").cast("decimal(6,6)")).cast("decimal(18,6)")
    out = sums.join(F.broadcast(price_list), ["provider_id", "model_id"]).withColumns({"cost_prompt": money("p", "usd_per_m_prompt"), "cost_completion": money("c", "usd_per_m_completion")})
    return out.select("provider_id", "model_id", "calls", "cost_prompt", "cost_completion", (F.col("cost_prompt") + F.col("cost_completion")).cast("decimal(18,6)").alias("cost_total"))


def cost_ratio(costs: DataFrame) -> DataFrame:
    """Every pair of models, dearer over cheaper; the table has a row for each model."""
    a, b = costs.select(F.col("model_id").alias("dearer"), F.col("cost_total").alias("x")), costs.select(F.col("model_id").alias("cheaper"), F.col("cost_total").alias("y"))
    return a.join(F.broadcast(b), F.expr("x > y")).select("dearer", "cheaper", (F.col("x").cast("double") / F.col("y").cast("double")).alias("ratio"))


def throughput(log: DataFrame, by: list[str] | None = None, start: str = "start_s", end: str = "end_s") -> DataFrame:
    """Calls a minute between the first start and the last end."""
    return log.groupBy(*(by or [])).agg(F.count("*").alias("calls"), (F.max(end) - F.min(start)).alias("makespan_s")).withColumn("per_minute", F.try_divide(F.col("calls") * 60.0, "makespan_s"))


def latency(log: DataFrame, value: str = "latency_ms", by: list[str] | None = None, exact: bool = True) -> DataFrame:
    q = F.percentile if exact else (lambda c, p: F.percentile_approx(c, p, 10_000))
    return log.groupBy(*(by or [])).agg(q(value, 0.5).alias("p50"), q(value, 0.99).alias("p99"), F.count(value).alias("calls"))


def speedup(fast: DataFrame, slow: DataFrame) -> DataFrame:
    return fast.select(F.col("per_minute").alias("fast")).crossJoin(slow.select(F.col("per_minute").alias("slow"))).withColumn("speedup", F.col("fast") / F.col("slow"))


def overhead(log: DataFrame, ideal_s: Column, total_s: Column) -> DataFrame:
    """Share of the total that is not ideal work, by size."""
    return log.withColumn("overhead", F.try_divide(total_s - ideal_s, total_s))


def savings(with_cost: float, without_cost: float) -> float:
    return 1 - with_cost / without_cost


def inflight(log: DataFrame, start: str = "start_s", end: str = "end_s", width: int = 60) -> DataFrame:
    """Most calls under way by minute: each call is counted in the minutes that it touches."""
    at = log.select(F.explode(F.sequence(F.floor(F.col(start) / width), F.floor(F.col(end) / width))).alias("minute"))
    return at.groupBy("minute").agg(F.count("*").alias("calls"))


def limits(log: DataFrame, rpm: int, tpm: int, time: str = "start_s") -> DataFrame:
    """Calls and tokens started in the 60 s up to each start, by lane, and which limit they exceed."""
    w = Window.partitionBy("lane").orderBy(time).rangeBetween(-60, 0)
    seen = log.withColumns({"calls_60": F.count("*").over(w), "tokens_60": F.sum("tokens").over(w)})
    return seen.withColumn("binds", F.when(F.col("calls_60") > rpm, "requests").when(F.col("tokens_60") > tpm, "tokens").otherwise("none"))
