"""Shared plumbing of the corpus operators: table access, shared folders, graph components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Read one table with Spark's reader only, so any store that Spark can open works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new folder name inside the folder the cluster shares.

    ``spark.checkpoint.dir`` is read from the session. Only where it is unset, as in tests on one
    machine, a temporary folder is made and set as the checkpoint folder.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            base = held.get()
        else:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster shares")
            base = "file://" + tempfile.mkdtemp(prefix="evalengine-")
            spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/evalengine-{uuid.uuid4().hex}"


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage through a Parquet table in the shared folder; it survives lost executors."""
    spark = df.sparkSession
    path = shared_dir(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Delete the files behind a ``checkpointed`` frame that nothing will read again."""
    spark = df.sparkSession
    for name in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def whole_text(name: str = "text") -> Column:
    """The text column with null read as the empty text."""
    return F.coalesce(F.col(name), F.lit(""))


def fold_of(folds: int, name: str = "doc_id") -> Column:
    """crc32 of the id written as decimal text, modulo ``folds``."""
    return F.crc32(F.col(name).cast("string").cast("binary")) % F.lit(folds)


def clear_of(df: DataFrame, *names: str) -> DataFrame:
    """Rename columns that would clash (whatever their case) with the names an operator adds."""
    taken = {n.lower() for n in names}
    for c in df.columns:
        if c.lower() in taken:
            df = df.withColumnRenamed(c, f"input_{c}")
    return df


def components(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """Connected components of an undirected edge list (columns ``a``, ``b``: long).

    Returns ``id``, ``component`` (the smallest id of the component) for every id that has an edge.
    Alternates the two star operations until every edge points at its component's smallest id. Each
    round is two aggregations with map-side combine and equi-joins that AQE may split; nothing is
    gathered on the driver but two numbers a round, and the lineage is cut in the shared folder.
    """
    e = edges.where("a IS NOT NULL AND b IS NOT NULL AND a <> b").select(
        F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")
    ).distinct()
    e = checkpointed(e)
    before = None
    for _ in range(max_rounds):
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionAll(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").where("v <> m").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        down = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(down, "hi").select(
            F.explode(F.array(F.struct("hi", F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("x")
        ).select("x.hi", "x.lo").where("hi <> lo").distinct()
        after = checkpointed(small)
        forget(e)
        e = after
        now = tuple(e.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")), F.lit(0))).first())
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("hi").alias("id"), F.col("lo").alias("component")).unionAll(e.select(F.col("lo").alias("id"), F.col("lo").alias("component"))).distinct()
