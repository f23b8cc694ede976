"""Sequence packing in the order of a space-filling curve.

1. One Arrow pass tokenizes every whole text (each distinct piece once), projects its hashed bag of tokens to four
   dimensions, and turns the grid cell into a Hilbert key. Beside the key it keeps the running crc32 of the ids
   at every ``STEP`` tokens, so that later cuts need no ids.
2. Rows (not texts or ids) are range-partitioned and sorted by key and id, so neighbours on the curve meet
   and equal keys spread over partitions.
3. Each range is packed in one pass: documents follow each other along the curve; one that does not fit is cut at
   a multiple of ``STEP``. The crc of a piece follows from the two running values at its ends.

Coordinates are squashed to the unit interval by a function that never reaches its ends, so no vector is clipped and
cells tell vectors apart at any size of the corpus.

Only the last sequence of a range is not full. Defined cases: null text is the empty text, whose only id is the
closing one; a document of any length spans as many sequences as it needs; rows that repeat an id are packed
each by itself; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import functools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import coded_chunks, gathered, sliced, summed
from evalengine.llm._common import checkpointed, table, whole_text
from evalengine.llm._merges import tokens
from evalengine.llm._shingles import mixed

LENGTH, STEP, CLOSING = 4096, 16, 2
DIMENSIONS, BITS, MIDDLE = 4, 10, 3.0
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def signs(ids: np.ndarray) -> np.ndarray:
    """What each token id adds to the projected document vector: +1 or -1 in each dimension, by its hash."""
    bits = mixed((ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(7)
    return np.column_stack([(bits >> np.uint64(3 * d) & np.uint64(1)).astype(np.int64) * 2 - 1 for d in range(DIMENSIONS)])


def coded(texts: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Token ids of all texts in a row, where each text's ids start, and each text's projected vector."""
    cut = coded_chunks(texts)
    ids, begin = tokens(path).of(cut.array)
    at, ends = gathered(begin, cut.codes)
    per_chunk, starts = summed(signs(ids), begin), ends[cut.starts]
    vector = np.column_stack([summed(per_chunk[:, d][cut.codes], cut.starts) for d in range(DIMENSIONS)])
    return ids[at], starts, vector / np.sqrt(np.maximum(np.diff(starts), 1))[:, None]


def hilbert_key(vectors: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Position along the Hilbert curve of each vector's cell in a grid over the squashed coordinates."""
    n = vectors.shape[1]
    x = ((0.5 + 0.5 * vectors / (MIDDLE + np.abs(vectors))) * (1 << bits)).astype(np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        for d in range(n):
            inverted = (x[:, d] & q) != 0
            swap = np.where(inverted, 0, (x[:, 0] ^ x[:, d]) & (q - 1))
            x[:, 0] ^= np.where(inverted, q - 1, swap)
            x[:, d] ^= swap
        q >>= 1
    for d in range(1, n):
        x[:, d] ^= x[:, d - 1]
    flip, q = np.zeros(len(x), np.int64), 1 << (bits - 1)
    while q > 1:
        flip ^= np.where((x[:, n - 1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= flip[:, None]
    key = np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        for d in range(n):
            key = key << 1 | (x[:, d] >> b & 1)
    return key


@functools.cache
def _zeros(log: int) -> tuple[int, ...]:
    """Columns of the crc32 operator that appends 2**log zero bytes."""
    if log:
        half = _zeros(log - 1)
        return tuple(_times(half, v) for v in half)
    return tuple(zlib.crc32(b"\0", (1 << i) ^ 0) ^ zlib.crc32(b"\0", 0) for i in range(32))


def _times(matrix: tuple[int, ...], v: int) -> int:
    out, i = 0, 0
    while v:
        if v & 1:
            out ^= matrix[i]
        v >>= 1
        i += 1
    return out


def crc_of_rest(whole: int, head: int, rest_bytes: int) -> int:
    """crc32 of what follows ``head`` in ``whole``, from both values and the length of the rest."""
    log = 0
    while rest_bytes:
        if rest_bytes & 1:
            head = _times(_zeros(log), head)
        rest_bytes >>= 1
        log += 1
    return whole ^ head


def tokenized(docs: DataFrame, path: str) -> DataFrame:
    """``doc_id``, ``key``, ``tokens`` and ``marks`` (running crc32 at every STEP tokens and at the end)."""

    last = np.array([CLOSING], "<u4").tobytes()

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        ids, starts, vectors = coded(batch.column(1), path)
        raw, marks = memoryview(ids.astype("<u4").tobytes()), []
        for i in range(batch.num_rows):
            body, crc, mine = raw[4 * starts[i] : 4 * starts[i + 1]], 0, []
            for k in range(0, len(body) // (4 * STEP) * 4 * STEP, 4 * STEP):
                crc = zlib.crc32(body[k : k + 4 * STEP], crc)
                mine.append(crc)
            mine.append(zlib.crc32(last, zlib.crc32(body[4 * STEP * len(mine) :], crc)))
            marks.append(np.array(mine, np.uint32).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(hilbert_key(vectors)), pa.array(np.diff(starts) + 1), pa.array(marks, pa.binary())], names=["doc_id", "key", "tokens", "marks"])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from sliced(run)(batches)
        tokens(path).forget()

    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    return read.mapInArrow(task, "doc_id long, key long, tokens long, marks binary")


def pack(docs: DataFrame, path: str, length: int = LENGTH) -> DataFrame:
    """The pieces of all documents (columns of ``PIECES``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sequence, offset = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            out = []
            for doc, tokens, marks in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "tokens", "marks")), strict=True):
                at, crc, before = 0, np.frombuffer(marks, np.uint32), 0
                while at < tokens:
                    room = length - offset
                    end = tokens if tokens - at <= room else at + room // STEP * STEP
                    if end == at:
                        sequence, offset = sequence + 1, 0
                        continue
                    now = int(crc[(end - 1) // STEP])
                    out.append((doc, at, end - at, crc_of_rest(now, before, 4 * (end - at)) if at else now, tokens, sequence, offset))
                    offset, at, before = offset + end - at, end, now
                    if offset == length:
                        sequence, offset = sequence + 1, 0
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    rows = checkpointed(tokenized(docs, path))
    return rows.repartitionByRange("key", "doc_id").sortWithinPartitions("key", "doc_id", "tokens").select("doc_id", "tokens", "marks").mapInArrow(run, PIECES)


def op5_curve_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
