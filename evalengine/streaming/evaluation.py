"""Streaming evaluation: windows over calls, duplicates, running intervals, and sinks that run to the end of the input."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from evalengine.functions.distributions import normal_quantile
from evalengine.sources.staging import shared_folder


def source(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A table as a stream of files; event times without a zone become timestamps, as watermarks need them."""
    schema = spark.read.parquet(f"{folder}/{name}.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", True).parquet(f"{folder}/{name}.parquet*")
    for f in schema:
        if f.dataType.typeName() == "timestamp_ntz":
            stream = stream.withColumn(f.name, F.col(f.name).cast("timestamp"))
    return stream


def per_minute(events: DataFrame, width: str = "1 minute", late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"))
    return w.agg(F.count("*").alias("calls"), F.count_if(F.col("event_type") == "error").alias("failed")).select(F.col("w.start").alias("start"), "calls", "failed")


def sliding(events: DataFrame, width: str, step: str, late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w"))
    return w.agg(F.count("*").alias("calls"), (1 - F.count_if(F.col("event_type") == "error") / F.count("*")).alias("pass_rate")).select(F.col("w.start").alias("start"), "calls", "pass_rate")


def sessions(events: DataFrame, gap: str, late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return w.agg(F.count("*").alias("calls")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "calls")


def distinct_requests(stream: DataFrame, key: str, time: str = "ts", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def running_interval(stream: DataFrame, value: str, by: list[str] | None = None, level: float = 0.95) -> DataFrame:
    """Count, mean and normal interval of all rows so far: additive state only."""
    v, z = F.col(value).cast("double"), normal_quantile((1 + level) / 2)
    m = stream.groupBy(*(by or [])).agg(F.count(v).alias("n"), F.avg(v).alias("value"), F.stddev_samp(v).alias("sd"))
    half = z * F.col("sd") / F.sqrt("n")
    return m.select(*(by or []), "n", "value", (F.col("value") - half).alias("ci_lo"), (F.col("value") + half).alias("ci_hi"))


def to_end(result: DataFrame, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Run a query over all input there is, and give what it wrote: rows that are appended go from the tasks to a table in the
    shared folder, whatever their number; what a later batch may change goes to a memory table."""
    spark = result.sparkSession
    q = result.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or shared_folder(spark, "stream")).trigger(availableNow=True)
    if mode == "append":
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(shared_folder(spark, "streamed"))
        store = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        q.format("parquet").option("path", path.toString()).start().awaitTermination()
        return spark.read.schema(result.schema).parquet(path.toString()) if store.exists(path) else spark.createDataFrame([], result.schema)
    name = f"stream_{uuid.uuid4().hex}"
    q.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def each_batch(stream: DataFrame, evaluate: Callable[[DataFrame, int], None], checkpoint: str):
    """Score each micro-batch; the cache makes repeated batches free of calls."""
    return stream.writeStream.foreachBatch(evaluate).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def attached(stream: DataFrame, known: DataFrame, key: str) -> DataFrame:
    """A stream beside a table that is read again in each batch; no state."""
    return stream.join(known, key)


def matched(asked: DataFrame, told: DataFrame, key: str, within: str, late: str = "10 minutes") -> DataFrame:
    """Requests and the responses of the same key that follow within a span; watermarks on both sides bound the state."""
    a = asked.withWatermark("ts", late).withColumnsRenamed({key: "_a", "ts": "_at"})
    b = told.withWatermark("ts", late).withColumnsRenamed({key: "_b", "ts": "_bt"})
    return a.join(b, F.expr(f"_a = _b AND _bt >= _at AND _bt <= _at + INTERVAL {within}"))


def lane_state(calls: DataFrame, lane: str, tokens: str) -> DataFrame:
    """Calls and tokens of each lane so far, as state that a restart takes up again: a row for each lane and batch."""
    kind = dict(calls.dtypes)[lane]

    def kept(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        calls_, spent = state.get if state.exists else (0, 0)
        for f in frames:
            calls_, spent = calls_ + len(f), spent + int(f[tokens].sum())
        state.update((calls_, spent))
        yield pd.DataFrame({lane: [key[0]], "calls": [calls_], "spent": [spent]})

    return calls.groupBy(lane).applyInPandasWithState(kept, f"{lane} {kind}, calls long, spent long", "calls long, spent long", "update", GroupStateTimeout.NoTimeout)
