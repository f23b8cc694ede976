"""Tables and the example sets derived from them; each is one narrow or equi-joined plan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from evalengine.functions.distributions import uniform


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def examples(spark: SparkSession, path: str, fmt: str, schema: StructType | str | None = None) -> DataFrame:
    """Example files: parquet, orc, csv (with header), json (lines) or text."""
    reader = spark.read.schema(schema) if schema is not None else spark.read
    return reader.option("header", True).format(fmt).load(path)


def bind(df: DataFrame, roles: dict[str, str | Column]) -> DataFrame:
    """``roles``: new name to column; unknown columns fail when the plan is analysed."""
    return df.select(*((F.col(c) if isinstance(c, str) else c).alias(r) for r, c in roles.items()))


def instruct(spark: SparkSession, folder: str) -> DataFrame:
    """Each user turn with the assistant turn right after it."""
    c = table(spark, folder, "conversations")
    asked = c.where("role = 'user'").select("conv_id", "turn", F.col("text").alias("instruction"))
    told = c.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("reference"))
    return asked.join(told, ["conv_id", "turn"]).select(F.concat_ws(":", "conv_id", "turn").alias("example_id"), "conv_id", "turn", "instruction", "reference")


def summarise(spark: SparkSession, folder: str) -> DataFrame:
    d = table(spark, folder, "documents")
    return d.select(F.col("doc_id").cast("string").alias("example_id"), "doc_id", "lang", "source", F.col("text").alias("body"), F.substring_index("text", "\n", 1).alias("reference"))


def factqa(spark: SparkSession, folder: str) -> DataFrame:
    words = F.split("text", " ")
    return table(spark, folder, "benchmark").select(
        F.col("item_id").cast("string").alias("example_id"), "item_id", F.array_join(F.slice(words, 1, 8), " ").alias("question"), F.array_join(F.slice(words, F.lit(9), F.size(words)), " ").alias("reference")
    )


def mixture(spark: SparkSession, folder: str) -> DataFrame:
    """The three domains with one schema."""
    a = instruct(spark, folder).select("example_id", F.lit("instruct").alias("domain"), F.col("instruction").alias("prompt"), "reference")
    b = summarise(spark, folder).select("example_id", F.lit("summarise").alias("domain"), F.col("body").alias("prompt"), "reference")
    c = factqa(spark, folder).select("example_id", F.lit("factqa").alias("domain"), F.col("question").alias("prompt"), "reference")
    return a.unionByName(b).unionByName(c)


def labelpair(spark: SparkSession, folder: str) -> DataFrame:
    """Two length rules against the quality label."""
    d, labels = table(spark, folder, "documents").select("doc_id", "n_chars"), table(spark, folder, "labels")
    right = lambda rule: (rule == (F.col("quality") == 1)).cast("int")
    return labels.join(d, "doc_id").select("doc_id", right(F.col("n_chars") > 800).alias("a"), right(F.col("n_chars") > 300).alias("b"))


def bulkpair(spark: SparkSession, folder: str) -> DataFrame:
    return table(spark, folder, "lineitem").select(F.col("l_discount").alias("a"), F.col("l_tax").alias("b"))


def ordinal(spark: SparkSession, folder: str) -> DataFrame:
    a = F.substring("o_orderpriority", 1, 1).cast("int")
    step = F.when(uniform(F.lit("ordinal"), "o_orderkey") < 0.3, 1).when(uniform(F.lit("ordinal"), "o_orderkey") > 0.8, -1).otherwise(0)
    return table(spark, folder, "orders").select(F.col("o_orderkey").alias("example_id"), a.alias("a"), F.greatest(F.lit(1), F.least(F.lit(5), a + step)).alias("b"))


def calllog(spark: SparkSession, folder: str, lanes: int) -> DataFrame:
    return table(spark, folder, "events").select(
        F.col("event_id").alias("call_id"), F.col("ts").cast("timestamp").alias("arrival"), (F.col("user_id") % lanes).cast("int").alias("lane"),
        F.ceil("value").cast("int").alias("tokens"), (F.col("value") * 8 + 200).alias("latency_ms"), (F.col("event_type") == "error").alias("failed"),
    )


def threads(spark: SparkSession, folder: str) -> DataFrame:
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    return table(spark, folder, "conversations").groupBy("conv_id").agg(turns.alias("turns"))


def segments(spark: SparkSession, folder: str) -> DataFrame:
    t = lambda n: table(spark, folder, n)
    return (
        t("lineitem").select("l_orderkey", F.col("l_discount").alias("value"))
        .join(t("orders").select("o_orderkey", "o_custkey"), F.expr("l_orderkey = o_orderkey"))
        .join(t("customer").select("c_custkey", "c_nationkey", "c_mktsegment"), F.expr("o_custkey = c_custkey"))
        .join(t("nation").select("n_nationkey", "n_name", "n_regionkey"), F.expr("c_nationkey = n_nationkey"))
        .join(t("region").select("r_regionkey", "r_name"), F.expr("n_regionkey = r_regionkey"))
        .select("value", "r_name", "n_name", "c_mktsegment")
    )


def catalog(spark: SparkSession, folder: str) -> DataFrame:
    from evalengine.functions.templating import estimated_tokens, render

    parts = render(table(spark, folder, "part"), "Describe {{ p_name }} by {{ p_brand | upper }}, a {{ p_type | lower }} of size {{ p_size }}, sold at {{ p_retailprice }}.")
    return parts.select("p_partkey", "prompt", estimated_tokens(F.col("prompt")).alias("est_tokens"))


def sampled(df: DataFrame, share: float, key: str, seed: int = 0) -> DataFrame:
    """The rows whose digest falls below ``share``; stable under any partitioning."""
    return df.where(uniform(F.lit(seed), key) < share)


def strip_html(html: Column) -> Column:
    out = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        out = F.replace(out, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(out, r"[ \t\n\r]+", " "))


def newest(df: DataFrame, keys: list[str], order: str) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(F.desc(order))
    return df.withColumn("rank", F.row_number().over(w)).where("rank = 1").drop("rank")
