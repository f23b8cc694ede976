"""Embedding near-duplicates by collision counting over one-dimensional projections.

1. Equal vectors of a label become one class. Each class is projected on many random directions. Groups of
   consecutive projections, cut into windows, make the keys of several tables; sorting by key brings together
   vectors whose windows agree.
2. Within a key, a vector is a query whose window is centred on its own projections: the number of projections in
   which another lies within ``WINDOW`` is the pair's collision count. Pairs whose count reaches a bound
   set for recall (``needed``) are verified by cosine. As a stream with leaders as its only state, a hot
   key costs one comparison for each leader, not for each pair. A vector follows a leader twice at most, in its batch and
   in its key, each time within ``FOLLOW`` of the threshold's distance; distance is a metric on the sphere, so the
   leaders that stand for two linked vectors are within 1 + 4 ``FOLLOW`` of it, and edges are kept up to there.
3. Inside the components of those edges, blocks of bounded size meet block against block, and a product in double
   precision finds every pair at or above the threshold. Counts and a spanning forest leave a block.

``table_recall`` gives the share of pairs at the threshold that some table brings together.

Defined cases: vectors that are null, zero, or hold null or non-finite components link with nothing, nor do vectors
without a label or of different lengths; equal vectors link (if valid); rows that repeat an id count as
vectors of their own; an empty table gives an empty result; extra columns are ignored; all arithmetic is in double
precision, and vectors are scaled by their largest component first, so that none is too small or too large.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import trimmed
from evalengine.llm._blocks import Linker, block_of, forest, met, verified
from evalengine.llm._common import checkpointed, components, table

THRESHOLD = 0.98
TABLES, TOGETHER, CELL, WINDOW, FOLLOW = 32, 5, 0.8, 0.6, 0.4
DIRECTIONS = TABLES * 3


def follow_near(threshold: float) -> tuple[float, float]:
    """Cosines at which a vector follows a leader, and at which it keeps an edge."""
    near = math.sqrt(max(0.0, 2 - 2 * threshold))
    at = lambda hops: 1 - (hops * near) ** 2 / 2
    return at(FOLLOW), at(1 + 4 * FOLLOW)


def needed(near: float, recall: float = 0.999999) -> int:
    """The collision count that a pair of cosine ``near`` reaches with the given probability."""
    spread = math.sqrt(2 - 2 * near)
    p = math.erf(WINDOW / spread / math.sqrt(2))
    below, k = 0.0, 0
    while k < DIRECTIONS and (below := below + math.comb(DIRECTIONS, k) * p**k * (1 - p) ** (DIRECTIONS - k)) < 1 - recall:
        k += 1
    return k


def table_recall(threshold: float = THRESHOLD) -> float:
    spread = math.sqrt(2 - 2 * threshold)
    grid = np.linspace(-CELL, CELL, 20001)
    density = np.exp(-(grid**2) / (2 * spread**2)) / (spread * math.sqrt(2 * math.pi))
    same = float(((1 - np.abs(grid) / CELL) * density).sum() * (grid[1] - grid[0]))
    return 1 - (1 - same**TOGETHER) ** TABLES


def unit(vectors: np.ndarray) -> np.ndarray:
    v = vectors / np.abs(vectors).max(axis=1, keepdims=True)
    return v / np.linalg.norm(v, axis=1, keepdims=True)


@functools.cache
def _directions(width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    rng = np.random.default_rng(7_000_003 + width)
    a, shift = rng.standard_normal((width, DIRECTIONS)), rng.uniform(0, CELL, DIRECTIONS)
    own = [[3 * t + k for k in range(3)] for t in range(TABLES)]
    return a, shift, np.array([[*mine, *rng.choice(np.setdiff1d(np.arange(DIRECTIONS), mine), TOGETHER - 3, replace=False)] for mine in own])


def gather(ids: np.ndarray, v: np.ndarray, p: np.ndarray, leaders: list, follow: float, near: float, need: int) -> list[tuple[int, int]]:
    """Cluster the vectors of one key around ``leaders`` (extended in place): count collisions, verify, keep edges."""
    edges: list[tuple[int, int]] = []
    free = np.ones(len(ids), bool)

    def compare(leader: tuple) -> None:
        hit = np.flatnonzero((np.abs(p - leader[2]) <= WINDOW).sum(axis=1) >= need)
        c = v[hit] @ leader[1]
        edges.extend((int(ids[i]), leader[0]) for i in hit[c >= near] if ids[i] != leader[0])
        free[hit[c >= follow]] = False

    for leader in leaders:
        compare(leader)
    while free.any():
        k = int(np.flatnonzero(free)[0])
        leaders.append((int(ids[k]), v[k], p[k]))
        free[k] = False
        compare(leaders[-1])
    return edges


def candidates(classes: DataFrame, threshold: float) -> DataFrame:
    """Edges ``a``, ``b`` between classes of a label that may hold a link, as spanning forests."""
    follow, near = follow_near(threshold)
    need = needed(near)

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, labels = batch.column(0).to_numpy(), batch.column(1).to_numpy().astype(np.int64)
            listed = batch.column(2)
            widths = np.diff(np.asarray(listed.offsets))
            flat, starts = listed.flatten().to_numpy(), np.asarray(listed.offsets) - listed.offsets[0].as_py()
            for width in np.unique(widths):
                rows = np.flatnonzero(widths == width)
                raw = flat[starts[rows][:, None] + np.arange(width)]
                a, shift, groups = _directions(int(width))
                v = unit(raw)
                p = v @ a
                cells = np.floor((p + shift) / CELL).astype(np.int64)
                keys, owner, edges = [], [], []
                for t in range(TABLES):
                    h = (labels[rows] * np.int64(1_000_003) + t * 97 + int(width) * 7919).astype(np.uint64)
                    for k in groups[t]:
                        h = (h ^ cells[:, k].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
                        h ^= h >> np.uint64(29)
                    order = np.argsort(h, kind="stable")
                    edge = np.flatnonzero(np.concatenate(([True], np.diff(h[order]) != 0, [True])))
                    alone = np.diff(edge) == 1
                    chosen = [order[edge[:-1][alone]]]
                    for x, y in zip(edge[:-1][~alone], edge[1:][~alone], strict=True):
                        at, leaders = order[x:y], []
                        edges += gather(ids[rows][at], v[at], p[at], leaders, follow, near, need)
                        kept = {x[0] for x in leaders}
                        chosen.append(np.array([i for i in at if int(ids[rows][i]) in kept], np.int64))
                    chosen = np.concatenate(chosen)
                    keys.append(h[chosen].view(np.int64))
                    owner.append(chosen)
                owner = np.concatenate(owner)
                for c in range(0, len(owner), 20_000):
                    o = owner[c : c + 20_000]
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)[c : c + 20_000]), pa.array(ids[rows][o]), pa.nulls(len(o), pa.int64()), pa.array([raw[i].tobytes() for i in o], pa.binary())], names=["key", "id", "other", "vector"])
                if edges := forest(edges):
                    x, y = np.array(edges, np.int64).T
                    yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(x), pa.array(y), pa.nulls(len(x), pa.binary())], names=["key", "id", "other", "vector"])

    def sorted_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, leaders = None, []
        for batch in batches:
            edges = []
            key, ids, other, vector = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_pylist(), batch.column(3)
            starts = np.flatnonzero(np.concatenate(([True], np.diff(key) != 0))) if len(key) else []
            for x, y in zip(starts, [*starts[1:], len(key)], strict=True):
                edges += [(int(ids[i]), other[i]) for i in range(x, y) if other[i] is not None]
                if key[x] != last:
                    last, leaders = key[x], []
                    if y - x == 1 and y < len(key):
                        continue
                rows = [i for i in range(x, y) if other[i] is None]
                if rows:
                    raw = [np.frombuffer(vector[i].as_py(), np.float64) for i in rows]
                    if len({len(r) for r in raw} | {len(m[1]) for m in leaders}) == 1:
                        v = unit(np.array(raw))
                        edges += gather(ids[rows], v, v @ _directions(v.shape[1])[0], leaders, follow, near, need)
            if edges := forest(edges):
                x, y = np.array(edges, np.int64).T
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], names=["a", "b"])

    read = classes.select("id", F.col("label").cast("long"), F.col("embedding").cast("array<double>"))
    return read.mapInArrow(trimmed(keyed), "key long, id long, other long, vector binary").repartition("key").sortWithinPartitions("key", "id").mapInArrow(trimmed(sorted_keys), "a long, b long")


def cosine(threshold: float) -> Linker:
    def linked(payloads: list[bytes]) -> np.ndarray:
        v = np.array([np.frombuffer(p, np.float64) for p in payloads])
        v = v / np.abs(v).max(axis=1, keepdims=True)
        norm = np.linalg.norm(v, axis=1)
        return (v @ v.T) / (norm[:, None] * norm[None, :]) >= threshold

    return linked


def _packed(items: DataFrame) -> DataFrame:
    """``embedding`` as the bytes of its doubles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array([np.array(v, np.float64).tobytes() for v in batch.column(batch.num_columns - 1).to_pylist()], pa.binary())], names=[*batch.schema.names[:-1], "vector"])

    return items.select("id", "component", "copies", "blocks", "block", "embedding").mapInArrow(run, "id long, component long, copies long, blocks int, block int, vector binary")


def dedup(vectors: DataFrame, threshold: float = THRESHOLD, block: int = 256) -> DataFrame:
    """A row for each vector: ``vec_id``, ``n_links``, ``component_id``, ``kept``."""
    whole = F.col("embedding").isNotNull() & (F.size("embedding") > 0)
    finite = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    valid = F.col("label").isNotNull() & F.col("vec_id").isNotNull() & whole & finite & F.exists("embedding", lambda x: x != 0)
    digest = F.when(F.coalesce(valid, F.lit(False)), F.concat_ws(" ", F.col("label"), F.size("embedding"), F.hex(F.xxhash64(F.lit(1), "embedding")), F.hex(F.xxhash64(F.lit(2), "embedding"))))
    read = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").cast("array<double>").alias("embedding")).withColumn("digest", digest)
    classes = checkpointed(read.where("digest IS NOT NULL").groupBy("digest").agg(F.min("vec_id").alias("id"), F.count("*").alias("copies"), F.first("label").alias("label"), F.first("embedding").alias("embedding")))
    near = components(candidates(classes, threshold))
    blocks = near.groupBy("component").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks"))
    items = classes.join(near, "id").join(blocks, "component").withColumn("block", block_of("id", F.col("blocks")))
    found = checkpointed(verified(met(_packed(items)), cosine(threshold), "vector"))
    joined = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("id").agg(F.sum("copies").alias("linked"))
    of_class = classes.select("id", "digest", "copies").join(links, "id", "left").join(joined, "id", "left").select("digest", (F.coalesce("linked", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    return read.select("vec_id", "digest").join(of_class, "digest", "left").select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"),
    ).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op8_collision_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "embeddings"))
