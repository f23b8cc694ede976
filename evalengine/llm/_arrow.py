"""Work on Arrow text columns by distinct chunk instead of by occurrence."""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql.types import StructField, StructType

from evalengine.llm._common import clear_of


def strings(values: pa.Array) -> list:
    """A string array as a list, by the quick way."""
    return values.to_numpy(zero_copy_only=False).tolist()


def joined(values: pa.Array, by: str) -> str:
    """All strings of an array in one."""
    if not len(values):
        return ""
    return pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), values), by)[0].as_py()


@dataclass
class Chunks:
    """Texts cut at single spaces. ``codes[starts[i]:starts[i+1]]`` index ``array`` for text i (one empty chunk for an empty text)."""

    array: pa.Array
    codes: np.ndarray
    starts: np.ndarray

    @functools.cached_property
    def chunks(self) -> list[str]:
        return strings(self.array)

    def odd(self) -> list[int]:
        """The texts in which a cut may fall inside a run of white space."""
        loose = np.array([not w or w[-1].isspace() for w in self.chunks], bool)
        where = np.flatnonzero(loose[self.codes]) if len(self.codes) else np.zeros(0, np.int64)
        return np.unique(np.searchsorted(self.starts, where, side="right") - 1).tolist()


def coded_chunks(texts: pa.Array) -> Chunks:
    lists = pc.split_pattern(texts, " ")
    starts = np.asarray(lists.offsets).astype(np.int64)
    starts -= starts[0]
    coded = lists.flatten().dictionary_encode()
    return Chunks(coded.dictionary, np.asarray(coded.indices).astype(np.int64), starts)


def small(batch: pa.RecordBatch, size: int = 6_000_000) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about ``size`` bytes each, so that a worker's memory follows the slice and not the batch."""
    step = max(1, int(batch.num_rows * size // max(1, batch.nbytes)))
    for at in range(0, batch.num_rows, step):
        yield batch.slice(at, step)


def trim() -> None:
    """Give freed memory back to the system, so that a reused worker starts its next task small."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # other C libraries than glibc
        pass


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A function for mapInArrow that trims the worker at the end of the task."""

    def over(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            trim()

    return over


def sliced(run: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]], size: int = 6_000_000) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A function for mapInArrow that hands slices of every batch to ``run``; ``trimmed``."""

    def over(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in small(whole, size):
                yield from run(batch)

    return trimmed(over)


@dataclass
class Pieces:
    """The pieces of distinct chunks: those of chunk c are ``codes[starts[c]:starts[c+1]]``, which index ``pieces``."""

    pieces: pa.Array
    codes: np.ndarray
    starts: np.ndarray


def split_chunks(chunks: pa.Array, pattern: str) -> Pieces:
    """Cut distinct chunks at matches of an RE2 pattern; empty pieces go."""
    lists = pc.split_pattern_regex(chunks, pattern)
    ends = np.asarray(lists.offsets).astype(np.int64)
    flat = lists.flatten()
    full = pc.not_equal(flat, "")
    at = np.concatenate(([0], np.cumsum(full.to_numpy(zero_copy_only=False))))
    coded = flat.filter(full).dictionary_encode()
    return Pieces(coded.dictionary, np.asarray(coded.indices).astype(np.int64), at[ends - ends[0]])


def gathered(starts: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the items of segments ``codes`` in the items' array, and where each segment's items begin in the result."""
    sizes = np.diff(starts)[codes]
    ends = np.concatenate(([0], np.cumsum(sizes)))
    return np.repeat(starts[:-1][codes] - ends[:-1], sizes) + np.arange(ends[-1]), ends


def summed(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sums of ``values`` over the rows starts[i]:starts[i+1]; empty ranges give 0. Sums of integers are exact."""
    kind = np.int64 if np.issubdtype(values.dtype, np.integer) or values.dtype == bool else np.float64
    total = np.concatenate((np.zeros((1, *values.shape[1:]), kind), np.cumsum(values, axis=0, dtype=kind)))
    return total[starts[1:]] - total[starts[:-1]]


def appended(df: DataFrame, added: str, columns: Callable[[pa.RecordBatch], list]) -> DataFrame:
    """``df`` with the columns ``added`` (a DDL list) that ``columns`` computes from each Arrow batch.

    One narrow step; every column of ``df`` passes through. Columns whose names clash are renamed first
    to ``input_<name>``.
    """
    extra = StructType.fromDDL(added)
    df = clear_of(df, *extra.names)

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([*batch.columns, *columns(batch)], names=[*batch.schema.names, *extra.names])

    return df.mapInArrow(sliced(run), StructType([*(StructField(f.name, f.dataType, True) for f in df.schema), *extra]))
