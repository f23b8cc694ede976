"""N-gram Jaccard similarity join: MinHash banding, shuffled on band hashes, verified on full n-gram sets.

1. One Arrow pass makes MinHash signatures. Within each batch, the documents of a band bucket are clustered
   around leaders by a one-byte-per-hash sketch; only leaders go to the shuffle, followers become edges.
   A hot group of copies so costs one row for each batch and band, not one for each copy.
2. Rows are shuffled on the band hash and each bucket is clustered the same way, as a stream with the leaders
   as its only state. The edges' components hold every pair that shares a bucket and may reach the threshold:
   Jaccard distance is a metric, so two texts near one another are both near the leader of either, and an
   edge is kept far below the threshold.
3. Inside a component, texts that are equal count once. Their full shingle sets meet in blocks of bounded
   size, block against block, where a matrix product gives every exact intersection. Only each text's
   number of links and a spanning forest of the links leave a block; pairs are never written out.

``bands`` and ``rows`` set the recall: a pair of similarity s shares a bucket with 1-(1-s^rows)^bands, and the
default of 20 bands of 4 rows gives 0.99997 at 0.8 (``recall``).

Defined cases: null text is the empty text; texts of fewer words than ``width`` have one shingle of all of
them, so that all texts without words are equal; a row with a null id links with nothing; rows that repeat
an id share its class, and where their texts differ each text keeps its links and the id's counts are their sums
(``_each_text``; near texts of one id count as linked there, but an id near itself only has no link); an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import small, trimmed
from evalengine.llm._blocks import Linker, block_of, forest, met, verified
from evalengine.llm._common import checkpointed, components, table, whole_text
from evalengine.llm._shingles import sets_of, shingles

FOLLOW, NEAR = 0.7, 0.15


def recall(similarity: float, bands: int, rows: int) -> float:
    return 1 - (1 - similarity**rows) ** bands


def signatures(texts: pa.Array, hashes: int, width: int) -> np.ndarray:
    h, ends = shingles(texts, width)
    rng = np.random.default_rng(20240229)
    out = np.empty((len(texts), hashes), np.uint32)
    for k in range(hashes):
        a, b = rng.integers(1, 1 << 63, 2, dtype=np.uint64)
        out[:, k] = np.minimum.reduceat((h * (a | np.uint64(1)) + b) >> np.uint64(32), ends[:-1]) if len(h) else 0
    return out


def lead(ids: list[int], sketches: np.ndarray, leaders: list[tuple[int, np.ndarray]]) -> list[tuple[int, int]]:
    """Cluster documents of one bucket around ``leaders`` (extended in place); returns edges."""
    edges = []
    for i, s in zip(ids, sketches, strict=True):
        joined = False
        if leaders:
            likeness = ((np.array([x[1] for x in leaders]) == s).mean(axis=1) - 1 / 256) / (1 - 1 / 256)
            for at in np.flatnonzero(likeness >= NEAR):
                if leaders[at][0] != i:
                    edges.append((i, leaders[at][0]))
                joined |= likeness[at] >= FOLLOW
        if not joined:
            leaders.append((i, s))
    return edges


def candidates(docs: DataFrame, bands: int, rows: int, width: int) -> DataFrame:
    """Edges ``a``, ``b`` between ids that share a band bucket, a forest of each bucket's near documents."""
    schema = "key long, id long, other long, sketch binary"

    def signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in small(whole, 8_000_000)):
            sig = signatures(batch.column(1), bands * rows, width)
            ids = batch.column(0).to_numpy()
            brief = (sig & 255).astype(np.uint8)
            keys, owner, edges = [], [], []
            for b in range(bands):
                key = np.full(len(ids), b + 1, np.uint64)
                for r in range(rows):
                    key = (key ^ sig[:, b * rows + r]) * np.uint64(0x9E3779B97F4A7C15)
                    key ^= key >> np.uint64(32)
                order = np.argsort(key, kind="stable")
                edge = np.flatnonzero(np.concatenate(([True], np.diff(key[order]) != 0, [True])))
                alone = np.diff(edge) == 1
                chosen = [order[edge[:-1][alone]]]
                for x, y in zip(edge[:-1][~alone], edge[1:][~alone], strict=True):
                    at, leaders = order[x:y], []
                    same = np.unique(brief[at], axis=0, return_index=True, return_inverse=True)
                    first = at[same[1]]
                    inverse = same[2].reshape(-1)
                    edges += [(int(ids[i]), int(ids[first[g]])) for i, g in zip(at, inverse, strict=True) if ids[i] != ids[first[g]]]
                    tagged: list = leaders
                    edges += lead([int(ids[i]) for i in first], brief[first], tagged)
                    kept = {x[0] for x in leaders}
                    chosen.append(np.array([i for i in first if int(ids[i]) in kept], np.int64))
                chosen = np.concatenate(chosen)
                keys.append(key[chosen].view(np.int64))
                owner.append(chosen)
            owner = np.concatenate(owner)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(ids[owner]), pa.nulls(len(owner), pa.int64()), pa.array([brief[i].tobytes() for i in owner], pa.binary())], names=["key", "id", "other", "sketch"])
            if edges := forest(edges):
                a, b = np.array(edges, np.int64).T
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(a), pa.array(b), pa.nulls(len(a), pa.binary())], names=["key", "id", "other", "sketch"])

    def bucketed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, leaders = None, []
        for batch in batches:
            edges = []
            key, ids, other = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_pylist()
            sketch = batch.column(3)
            starts = np.flatnonzero(np.concatenate(([True], np.diff(key) != 0))) if len(key) else []
            for x, y in zip(starts, [*starts[1:], len(key)], strict=True):
                if key[x] != last:
                    last, leaders = key[x], []
                    if y - x == 1 and y < len(key):
                        if other[x] is not None:
                            edges.append((int(ids[x]), other[x]))
                        continue
                for i in range(x, y):
                    if other[i] is not None:
                        edges.append((int(ids[i]), other[i]))
                    else:
                        edges += lead([int(ids[i])], np.frombuffer(sketch[i].as_py(), np.uint8)[None, :], leaders)
            if edges := forest(edges):
                a, b = np.array(edges, np.int64).T
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    read = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("id"), whole_text().alias("text"))
    return read.mapInArrow(trimmed(signed), schema).repartition("key").sortWithinPartitions("key", "id").mapInArrow(trimmed(bucketed), "a long, b long")


def jaccard(threshold: float) -> Linker:
    """Links between sets of 64-bit hashes, exactly: common * 1000 >= threshold * 1000 * union."""
    part, whole, wide = round(threshold * 1000), 1000, 4096

    def linked(payloads: list[bytes]) -> np.ndarray:
        found = [np.frombuffer(p, np.uint64) for p in payloads]
        sizes = np.array([len(s) for s in found], np.int64)
        values, column = np.unique(np.concatenate(found), return_inverse=True)
        owner = np.repeat(np.arange(len(found)), sizes)
        shared = np.bincount(column, minlength=len(values)) > 1
        keep = shared[column]
        place, owner = (np.cumsum(shared) - 1)[column[keep]], owner[keep]
        order = np.argsort(place, kind="stable")
        place, owner = place[order], owner[order]
        common = np.zeros((len(found), len(found)), np.int64)
        for c in range(0, int(shared.sum()), wide):
            x, y = np.searchsorted(place, (c, c + wide))
            m = np.zeros((len(found), wide), np.float32)
            m[owner[x:y], place[x:y] - c] = 1
            common += (m @ m.T).astype(np.int64)
        return common * whole >= part * (sizes[:, None] + sizes[None, :] - common)

    return linked


def join(docs: DataFrame, threshold: float = 0.8, width: int = 5, bands: int = 20, rows: int = 4, block: int = 192) -> DataFrame:
    """A row for each document: ``doc_id``, ``class_id`` (smallest id reachable by links), ``text_id`` (smallest id
    with the same text), ``n_links`` (other documents linked directly, copies included), ``n_text_links`` (other
    texts linked) and ``kept`` (doc_id = class_id)."""
    near = components(candidates(docs, bands, rows, width))
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(whole_text().cast("binary"), 256).alias("digest"))
    members = checkpointed(ids.join(near, ids["doc_id"] == near["id"]).select("doc_id", "component", "digest").groupBy("doc_id", "component").agg(F.min("digest").alias("digest"), (F.min("digest") != F.max("digest")).alias("mixed")))
    if not members.where("mixed").isEmpty():
        return _each_text(docs, threshold, width, bands, rows, block)
    texts = members.groupBy("component", "digest").agg(F.min("doc_id").alias("id"), F.count("*").alias("copies"))
    counted = texts.groupBy("component").agg(F.count("*").alias("n")).where("n > 1").withColumn("blocks", F.ceil(F.col("n") / block).cast("int"))
    placed = texts.join(counted, "component").select("id", "component", "copies", "blocks", block_of("id", F.col("blocks")).alias("block"))
    read = docs.select(F.col("doc_id").cast("long").alias("id"), whole_text().alias("text")).join(placed, "id")

    def shingled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in small(whole):
                found = pa.array([s.tobytes() for s in sets_of(batch.column(1), width)], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0), *batch.columns[2:], found], names=["id", "component", "copies", "blocks", "block", "shingles"])

    sets = read.select("id", "text", "component", "copies", "blocks", "block").mapInArrow(trimmed(shingled), "id long, component long, copies long, blocks int, block int, shingles binary")
    found = checkpointed(verified(met(sets), jaccard(threshold), "shingles"))
    joined = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("id").agg(F.sum("items").alias("texts"), F.sum("copies").alias("documents"))
    of_text = texts.join(links, "id", "left").join(joined.withColumnRenamed("component", "class"), "id", "left")
    of_doc = members.join(of_text.withColumnRenamed("id", "text_id"), ["component", "digest"]).groupBy("doc_id").agg(
        F.min(F.coalesce("class", "text_id")).alias("class_id"), F.min("text_id").alias("text_id"),
        F.max(F.coalesce("documents", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.max(F.coalesce("texts", F.lit(0))).alias("n_text_links"),
    )
    return ids.select("doc_id").join(of_doc, "doc_id", "left").select(
        "doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("text_id", "doc_id").alias("text_id"),
        F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("n_text_links", F.lit(0)).cast("long").alias("n_text_links"),
        F.coalesce(F.col("class_id") == F.col("doc_id"), F.lit(True)).alias("kept"),
    )


def _each_text(docs: DataFrame, *how) -> DataFrame:
    """``join`` where an id has near rows of different texts: its different texts are joined under row numbers, and
    their classes become one."""
    whole = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    own = whole.where("doc_id IS NOT NULL").withColumn("digest", F.sha2(F.col("text").cast("binary"), 256)).dropDuplicates(["doc_id", "digest"])
    numbered = checkpointed(own.select("doc_id", "text", F.monotonically_increasing_id().alias("row")))
    found = join(numbered.select(F.col("row").alias("doc_id"), "text"), *how).withColumnsRenamed({"doc_id": "row", "class_id": "class"}).drop("kept")
    per = checkpointed(numbered.select("doc_id", "row").join(found, "row"))
    lowest = per.groupBy("doc_id").agg(F.min("class").alias("low"))
    merged = components(per.join(lowest, "doc_id").select(F.col("class").alias("a"), F.col("low").alias("b")))
    top = per.join(merged, per["class"] == merged["id"], "left").withColumn("top", F.coalesce("component", "class"))
    names = top.groupBy("top").agg(F.min("doc_id").alias("class_id"))
    same = per.groupBy("text_id").agg(F.min("doc_id").alias("same_id"))
    of_doc = top.join(names, "top").join(same, "text_id").groupBy("doc_id").agg(F.min("class_id").alias("class_id"), F.min("same_id").alias("text_id"), F.sum("n_links").alias("n_links"), F.sum("n_text_links").alias("n_text_links"))
    return whole.select("doc_id").join(of_doc, "doc_id", "left").select(
        "doc_id", "class_id", "text_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("n_text_links", F.lit(0)).alias("n_text_links"),
        F.coalesce(F.col("class_id") == F.col("doc_id"), F.lit(True)).alias("kept"),
    )


def op10_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(table(spark, sf_dir, "documents"))
