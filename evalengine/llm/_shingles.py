"""Hashed word shingles of Arrow text columns."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash

from evalengine.llm._arrow import coded_chunks

_P = np.uint64(0x9E3779B97F4A7C15)
_Q = np.uint64(0xBF58476D1CE4E5B9)


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * _Q
    return h ^ (h >> np.uint64(29))


def byte_hashes(values: pa.Array) -> np.ndarray:
    """A 64-bit hash of each string, from its bytes."""
    if not len(values):
        return np.zeros(0, np.uint64)
    values = pa.concat_arrays([values.cast(pa.binary())])
    ends = np.frombuffer(values.buffers()[1], np.int32)[values.offset : values.offset + len(values) + 1].astype(np.int64)
    raw = np.frombuffer(values.buffers()[2], np.uint8)[ends[0] : ends[-1]] if values.buffers()[2] is not None else np.zeros(0, np.uint8)
    size, begin = np.diff(ends), ends[:-1] - ends[0]
    place = np.arange(len(raw)) - np.repeat(begin, size)
    powers = np.multiply.accumulate(np.full(int(size.max()) + 1, _P))
    parts = np.append(mixed((raw.astype(np.uint64) + np.uint64(1)) * _Q) * powers[place], np.uint64(0))
    total = np.where(size > 0, np.add.reduceat(parts, begin), np.uint64(0))
    return mixed(total + size.astype(np.uint64) * _P)


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the white-space separated words of each text, and where each text's words start."""
    cut = coded_chunks(texts)
    found = [w.split() for w in cut.chunks]
    sizes = np.array([len(f) for f in found], np.int64)
    flat = np.array([xxhash.xxh3_64_intdigest(w) for f in found for w in f], np.uint64)
    begin = np.concatenate(([0], np.cumsum(sizes)))
    each = sizes[cut.codes]
    ends = np.concatenate(([0], np.cumsum(each)))
    hashes = flat[np.repeat(begin[cut.codes] - ends[:-1], each) + np.arange(ends[-1])] if len(flat) else np.zeros(0, np.uint64)
    return hashes, ends[cut.starts]


def shingles(texts: pa.Array, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the runs of ``width`` words of each text, repeats included, and their starts.

    A text of fewer words has one shingle, made of all of them; a text without words has the shingle of nothing.
    """
    words, starts = word_hashes(texts)
    n = np.diff(starts)
    made = np.maximum(n - width + 1, 1)
    ends = np.concatenate(([0], np.cumsum(made)))
    at = np.repeat(starts[:-1] - ends[:-1], made) + np.arange(ends[-1])
    length = np.repeat(np.minimum(n, width), made)
    padded = np.concatenate((words, np.zeros(width, np.uint64)))
    h = length.astype(np.uint64)
    for k in range(width):
        h = np.where(k < length, h * _P + padded[at + k], h)
    return mixed(h), ends


def sets_of(texts: pa.Array, width: int = 5) -> list[np.ndarray]:
    h, ends = shingles(texts, width)
    return [np.unique(h[ends[i] : ends[i + 1]]) for i in range(len(ends) - 1)]
