"""A content-addressed, versioned response cache on Parquet.

Segments are immutable folders; a version is a manifest file that lists segments and appears by a rename after its
number was claimed, so readers see whole versions and two writers cannot publish the same one. Manifests are read
through the file system, without jobs. Failed calls are returned with their error and never written.
"""

from __future__ import annotations

import json
import uuid
from datetime import datetime

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evalengine.sources.staging import staged

SCHEMA = (
    "cache_key string, model_id string, provider_id string, prompt_text string, response_text string, prompt_tokens int, completion_tokens int, "
    "latency_ms double, created_ts timestamp, ttl_days int, temperature double, max_tokens int, key_prefix string, version long"
)
POLICIES = ("read_write", "read_only", "write_only", "replay", "off")


class ReplayMiss(LookupError):
    """A replay met a request that the cache does not hold."""


def key_expr(prompt: Column, model: Column, provider: Column, temperature: Column, max_tokens: Column, framing: str = "length", params: Column | None = None) -> Column:
    """Digest of all that determines a response. ``length`` puts each field's length before it, so that fields cannot
    run into each other; ``plain`` only concatenates."""
    fields = [prompt, model, provider, temperature.cast("double").cast("string"), max_tokens.cast("string")]
    if params is not None:
        fields.append(F.to_json(F.map_from_entries(F.sort_array(F.map_entries(params)))))
    parts = [F.coalesce(f, F.lit("")) for f in fields]
    if framing == "length":
        parts = [x for p in parts for x in (F.length(p).cast("string"), F.lit(":"), p)]
    return F.sha2(F.concat(*parts), 256)


def live(entries: DataFrame, as_of: Column) -> DataFrame:
    """Entries without a time to live, or whose time ends after ``as_of``."""
    return entries.where(F.col("ttl_days").isNull() | (F.col("created_ts") + F.make_interval(days=F.col("ttl_days")) > as_of))


def latest(entries: DataFrame, order: str = "version") -> DataFrame:
    w = Window.partitionBy("cache_key").orderBy(F.desc(order), F.desc("created_ts"))
    return entries.withColumn("_n", F.row_number().over(w)).where("_n = 1").drop("_n")


class ResponseCache:
    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path = spark, path.rstrip("/")
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
        self._path = hadoop.Path
        self._fs = hadoop.Path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _versions(self) -> list[int]:
        """Committed versions, from the folder's listing alone."""
        folder = self._path(f"{self.path}/versions")
        names = [s.getPath().getName() for s in self._fs.listStatus(folder)] if self._fs.exists(folder) else []
        return sorted(int(n[:-5]) for n in names if n.endswith(".json"))

    def _manifest(self, version: int) -> dict:
        stream = self._fs.open(self._path(f"{self.path}/versions/{version}.json"))
        try:
            return json.loads(bytes(stream.readAllBytes()).decode())
        finally:
            stream.close()

    def _written(self, path: str, text: str, overwrite: bool) -> None:
        stream = self._fs.create(self._path(path), overwrite)
        stream.write(bytearray(text.encode()))
        stream.close()

    def version(self) -> int:
        return max(self._versions(), default=0)

    def commit(self, segments: list[str], at: datetime) -> int:
        """Publish a version that holds ``segments``. The number is claimed by creating a file that must not exist, which
        also stores without an exclusive rename refuse; the manifest is written aside and appears whole."""
        n = self.version() + 1
        self._fs.mkdirs(self._path(f"{self.path}/versions"))
        try:
            self._written(f"{self.path}/versions/{n}.claim", "", False)
        except Py4JJavaError as e:
            raise RuntimeError(f"version {n} was committed by another writer") from e
        aside = f"{self.path}/aside-{uuid.uuid4().hex}"
        self._written(aside, json.dumps({"segments": segments, "at": at.isoformat()}), True)
        if not self._fs.rename(self._path(aside), self._path(f"{self.path}/versions/{n}.json")):
            raise RuntimeError(f"version {n} could not be published")
        return n

    def segments(self, version: int | None = None, as_of: datetime | None = None) -> list[str]:
        """Segments of the newest version, or of the newest one up to a version or a time; one manifest is read, or those back to the time."""
        for v in reversed([v for v in self._versions() if version is None or v <= version]):
            m = self._manifest(v)
            if as_of is None or datetime.fromisoformat(m["at"]) <= as_of:
                return m["segments"]
        return []

    def read(self, version: int | None = None, as_of: datetime | None = None, keys: DataFrame | None = None) -> DataFrame:
        """The newest entry of each key, as of a version or a time. With ``keys`` (``cache_key``), only of those: entries
        are joined with them before anything is ranked, so texts of other keys are dropped at the scan's stage."""
        kept = self.segments(version, as_of)
        if not kept:
            return self.spark.createDataFrame([], SCHEMA)
        entries = self.spark.read.schema(SCHEMA).parquet(*(f"{self.path}/segments/{s}" for s in kept))
        return latest(entries if keys is None else entries.join(keys.select("cache_key"), "cache_key", "left_semi"))

    def put(self, entries: DataFrame, at: datetime) -> int:
        """Append entries as one segment and commit; an entry of a known key becomes its newest."""
        name, n = uuid.uuid4().hex, self.version() + 1
        rows = entries.withColumn("version", F.lit(n).cast("long")).withColumn("key_prefix", F.substring("cache_key", 1, 2))
        rows.select(*(c.split(" ")[0] for c in SCHEMA.split(", "))).sortWithinPartitions("cache_key").write.parquet(f"{self.path}/segments/{name}")
        return self.commit([*self.segments(), name], at)

    def compact(self, at: datetime) -> int:
        name = uuid.uuid4().hex
        self.read().repartition("key_prefix").sortWithinPartitions("cache_key").write.parquet(f"{self.path}/segments/{name}")
        return self.commit([name], at)

    def vacuum(self, keep: int = 1) -> int:
        """Delete segments that none of the last ``keep`` versions holds, and older manifests."""
        found = self._versions()
        recent = found[-keep:]
        used = {s for v in recent for s in self._manifest(v)["segments"]}
        gone = 0
        for s in self._fs.listStatus(self._path(f"{self.path}/segments")):
            if s.getPath().getName() not in used:
                self._fs.delete(s.getPath(), True)
                gone += 1
        for v in set(found) - set(recent):
            for end in ("json", "claim"):
                self._fs.delete(self._path(f"{self.path}/versions/{v}.{end}"), False)
        return gone

    def footprint(self) -> dict[str, float]:
        entries = self.read().count()
        size = sum(self._fs.getContentSummary(self._path(f"{self.path}/segments/{s}")).getLength() for s in self.segments())
        return {"bytes": size, "entries": entries, "bytes_per_entry": size / max(1, entries)}

    def resolve(self, requests: DataFrame, policy: str, call, at: datetime, ttl_days: int | None = None, ignore_ttl: bool = False) -> tuple[DataFrame, dict[str, int]]:
        """Responses for distinct requests (``cache_key``, ``prompt``, ``model_id``, ...) under a policy, and counts.

        ``call(requests) -> DataFrame`` adds ``response_text``, token counts, latency and, where it can fail, ``error``. A
        replay never builds it. A failed call is not written, so the next run calls again.
        """
        if policy not in POLICIES:
            raise ValueError(f"unknown policy {policy}")
        names = ["cache_key", "response_text", "prompt_tokens", "completion_tokens", "latency_ms"]
        none = {"hits": 0, "misses": 0, "calls": 0, "writes": 0}

        def called(asked: DataFrame) -> DataFrame:
            """The calls' rows, made once; every later read is of the table."""
            made = call(asked)
            return staged(made if "error" in made.columns else made.withColumn("error", F.lit(None).cast("string")))

        def given(rows: DataFrame, held: bool) -> DataFrame:
            return rows.select(*names, F.lit(None).cast("string").alias("error") if held else "error", F.lit(held).alias("from_cache"))

        if policy == "off":
            return given(called(requests), False), none | {"calls": requests.count()}
        found = self.read(keys=requests)
        if not ignore_ttl:
            found = live(found, F.lit(at))
        if policy == "write_only":
            hits, misses = None, requests
        else:
            hits = requests.select("cache_key").join(found.select(*names), "cache_key")
            misses = requests.join(found.select("cache_key"), "cache_key", "left_anti")
        if policy == "replay":
            lost = misses.select("cache_key").limit(20).collect()
            if lost:
                raise ReplayMiss(", ".join(r.cache_key for r in lost))
            return given(hits, True), none | {"hits": requests.count()}
        n_hits, n_misses = (0 if hits is None else hits.count()), misses.count()
        out = given(hits, True) if hits is not None else None
        writes = 0
        if n_misses:
            new = called(misses)
            if policy != "read_only":
                good = new.where("error IS NULL")
                writes = good.count()
                self.put(good.select(
                    "cache_key", "model_id", "provider_id", F.col("prompt").alias("prompt_text"), "response_text", "prompt_tokens", "completion_tokens", "latency_ms",
                    F.lit(at).cast("timestamp").alias("created_ts"), F.lit(ttl_days).cast("int").alias("ttl_days"), "temperature", "max_tokens",
                ), at)
            out = given(new, False) if out is None else out.unionByName(given(new, False))
        elif out is None:
            out = given(found, True).limit(0)
        return out, none | {"hits": n_hits, "misses": n_misses, "calls": n_misses, "writes": writes}
