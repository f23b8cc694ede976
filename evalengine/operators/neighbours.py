"""Nearest vectors of a set of queries, compared with all rows, block against block.

Vectors are packed once into blocks in the shared folder. Every block of queries meets every block of candidates: a matrix
product in single precision, ``SLICE`` queries at a time, passes what may be among the nearest, and only that is computed in double precision, in
the order of ``semantic.cosine``. The cut lies ``MARGIN`` below the k-th product or a lower bound of it, far more than rounding moves one, so nothing is
lost; of equal cosines the k smallest ids stay. A pair of blocks hands on about k rows a query.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evalengine.sources.staging import staged

QUERIES, ROWS, SLICE, MARGIN, PAIRS, GROUPS, TASKS = 2048, 4096, 256, 1e-4, 1 << 17, 64, 4
ODD = -1


def _packed(batch: pa.RecordBatch, size: int) -> Iterator[tuple]:
    """Blocks (ids, labels, length of the vectors, their numbers) of vectors of one length; ``ODD``: null, or with a null component."""
    ids, vectors, labels = batch.columns
    flat = vectors.flatten()
    width = pc.list_value_length(vectors).fill_null(ODD).to_numpy(zero_copy_only=False).astype(np.int64)
    begin = np.concatenate(([0], np.cumsum(np.maximum(width, 0))))
    lost = np.concatenate(([0], np.cumsum(flat.is_null().to_numpy(zero_copy_only=False)))) if flat.null_count else np.zeros(begin[-1] + 1, np.int64)
    width = np.where(lost[begin[1:]] > lost[begin[:-1]], ODD, width)
    numbers = flat.cast(pa.float64()).to_numpy(zero_copy_only=False)
    for w in np.unique(width).tolist():
        rows = np.flatnonzero(width == w)
        for k in range(0, len(rows), size):
            at = rows[k : k + size]
            cells = b"" if w <= 0 else numbers[(begin[at][:, None] + np.arange(w)).ravel()].tobytes()
            yield ids.take(pa.array(at)), labels.take(pa.array(at)), w, cells


def blocks(df: DataFrame, size: int) -> DataFrame:
    """``df`` has ``id`` long, ``vector`` and ``label``; blocks of up to ``size`` rows, staged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def out() -> Iterator[pa.RecordBatch]:
            whole = pa.Table.from_batches(held).combine_chunks().to_batches()
            held.clear()
            for batch in whole:
                for ids, labels, width, cells in _packed(batch, size):
                    one = lambda values: pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), values)
                    yield pa.RecordBatch.from_arrays([one(ids), one(labels), pa.array([width], pa.int32()), pa.array([cells], pa.binary())], names=["ids", "labels", "width", "cells"])

        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= size:
                yield from out()
        if held:
            yield from out()

    kind = df.schema["label"].dataType.simpleString()
    return staged(df.select("id", F.col("vector").cast("array<double>"), "label").where("id IS NOT NULL").mapInArrow(run, f"ids array<long>, labels array<{kind}>, width int, cells binary"))


def dealt(held: DataFrame) -> DataFrame:
    """Blocks over tasks, ``TASKS`` a core at least: those of one file are read by one task, which would do all its pairs of blocks."""
    most = max(held.rdd.getNumPartitions(), TASKS * held.sparkSession.sparkContext.defaultParallelism)
    return held.repartition(max(1, min(held.count(), most)))


def _in_order(x: np.ndarray, y: np.ndarray, i: np.ndarray | slice = slice(None), j: np.ndarray | slice = slice(None)) -> np.ndarray:
    """Dot products of columns i of x and j of y, summed in the order of the components (rows)."""
    s = np.float64(0)
    for a, b in zip(x, y, strict=True):
        s = s + a[i] * b[j]
    return s


def _unit(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n = np.sqrt(_in_order(x, x))
    return (x / np.where(n == 0, 1, n)).astype(np.float32), n


def _cut(about: np.ndarray, k: int) -> np.ndarray:
    """At most the k-th largest number of each row, from the largest of ``GROUPS`` groups: k of them are k numbers of the row."""
    n, m = about.shape
    if m <= k:
        return np.full(n, -np.inf, np.float32)
    kth = lambda x: np.partition(x, -k, axis=1)[:, -k]
    if m < 2 * GROUPS or k > GROUPS:
        return kth(about)
    cut = kth(about[:, : m // GROUPS * GROUPS].reshape(n, -1, GROUPS).max(axis=1))
    if len(few := np.flatnonzero(cut == -np.inf)):
        cut[few] = kth(about[few])
    return cut


def _near(q_ids: np.ndarray, c_ids: np.ndarray, q: np.ndarray | None, c: np.ndarray | None, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, candidate, cosine) by place: all that may be among the k nearest. A cosine that is not there is -inf, one that is no number inf, as they sort."""
    if q is None or c is None:  # no cosines: the smallest ids
        order = np.argsort(c_ids, kind="stable")
        i, j = (x.ravel() for x in np.meshgrid(np.arange(len(q_ids)), order, indexing="ij"))
        i, j = i[q_ids[i] != c_ids[j]], j[q_ids[i] != c_ids[j]]
        rank = np.arange(len(i)) - np.searchsorted(i, i)
        return i[rank < k], j[rank < k], np.full(int((rank < k).sum()), -np.inf)
    with np.errstate(all="ignore"):
        q, c = np.ascontiguousarray(q.T), np.ascontiguousarray(c.T)
        (qu, qn), (cu, cn) = _unit(q), _unit(c)
        odd, none = not (np.isfinite(qu).all() and np.isfinite(cu).all()), np.flatnonzero(cn == 0)
        both = np.flatnonzero(np.isin(c_ids, q_ids))
        found = []
        for at in range(0, len(q_ids), SLICE):
            part = slice(at, at + SLICE)
            about = qu[:, part].T @ cu
            if odd:
                about[np.isnan(about)] = np.inf
            about[qn[part] == 0] = -np.inf
            about[:, none] = -np.inf
            i, j = np.nonzero(q_ids[part, None] == c_ids[both])
            about[i, both[j]] = -np.inf
            i, j = np.nonzero(about >= (_cut(about, k) - np.float32(MARGIN))[:, None])
            found.append((i + at, j))
        i, j = (np.concatenate(x) for x in zip(*found, strict=True))
        other = q_ids[i] != c_ids[j]
        i, j = i[other], j[other]
        exact = np.empty(len(i))
        for at in range(0, len(i), PAIRS):
            a, b = i[at : at + PAIRS], j[at : at + PAIRS]
            n = qn[a] * cn[b]
            x = _in_order(q, c, a, b) / n
            exact[at : at + PAIRS] = np.where(n == 0, -np.inf, np.where(np.isnan(x), np.inf, x))
    order = np.lexsort((c_ids[j], -exact, i))
    i, j, exact = i[order], j[order], exact[order]
    # Of equal cosines the k first ids stay; then the k-th, and what rounding to nine places may raise to it.
    fresh = np.concatenate(([True], (np.diff(i) != 0) | (exact[1:] != exact[:-1]))) if len(i) else np.zeros(0, bool)
    place = np.arange(len(i))
    keep = place - np.maximum.accumulate(np.where(fresh, place, 0)) < k
    i, j, exact = i[keep], j[keep], exact[keep]
    begin = np.searchsorted(i, np.arange(len(q_ids)))
    size = np.searchsorted(i, np.arange(len(q_ids)), side="right") - begin
    last = np.full(len(q_ids), -np.inf)
    last[size >= k] = exact[begin[size >= k] + k - 1]
    keep = exact >= last[i] - 3e-9
    return i[keep], j[keep], exact[keep]


def nearest(queries: DataFrame, rows: DataFrame, k: int = 10) -> DataFrame:
    """The k rows of highest cosine (nine places; ties by id) of each query but itself: ``query_id``, ``rank``, ``cand_id``,
    ``cosine``, ``relevant`` (equal labels). Both inputs have ``id``, ``vector`` and ``label``.

    As in SQL, null cosines come last and those that are no number first.
    """
    packed = blocks(queries, QUERIES)
    packed = packed.coalesce(max(1, packed.count() // TASKS))  # blocks that a few queries of many files leave small share a task
    asked = packed.select(F.col("ids").alias("q_ids"), F.col("labels").alias("q_labels"), F.col("width").alias("q_width"), F.col("cells").alias("q_cells"))
    held = dealt(blocks(rows, ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                q_ids, q_labels, q_width, q_cells, c_ids, c_labels, c_width, c_cells = (c[r] for c in batch.columns)
                qi, ci, alike = q_ids.values.to_numpy(), c_ids.values.to_numpy(), q_width.as_py() == c_width.as_py() != ODD
                q, c = (np.frombuffer(x.as_buffer()).reshape(n, -1) if alike and x.as_buffer().size else None for x, n in ((q_cells, len(qi)), (c_cells, len(ci))))
                i, j, cosine = _near(qi, ci, q, c, k)
                number = pa.array(np.where(cosine == np.inf, np.nan, cosine), mask=cosine == -np.inf)
                yield pa.RecordBatch.from_arrays([pa.array(qi[i]), pa.array(ci[j]), number, pc.equal(q_labels.values.take(pa.array(i)), c_labels.values.take(pa.array(j)))], names=["query_id", "cand_id", "cosine", "relevant"])

    columns = ["q_ids", "q_labels", "q_width", "q_cells", "ids", "labels", "width", "cells"]
    found = asked.crossJoin(held).select(*columns).mapInArrow(run, "query_id long, cand_id long, cosine double, relevant boolean")
    w = Window.partitionBy("query_id").orderBy(F.desc("cosine"), "cand_id")
    return found.withColumn("cosine", F.round("cosine", 9)).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
