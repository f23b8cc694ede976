"""Language-model scoring with an n-gram trie in Elias-Fano levels.

Texts are tokenized once; a table in the shared folder holds, for each slice of texts, its distinct words' hashes and the
places of its tokens. Words are counted first, which gives each an id. One more pass then sends, for each shard, a run
of the slice's sorted trigrams and their counts; bigrams are their prefixes, and a text's last bigram is a
trigram without a third word. Counting is exact, covers the corpus, and keeps n-grams that occur once.

A shard is a file that workers map into memory. Its two levels are

* ``contexts`` and ``begin``: the first words, and where their second words start (monotone both); ``follow``: where each
  bigram's third words start;
* ``second`` and ``third``: word ids. Adding to each range the last value before it makes the whole level
  monotone, so that one successor search relative to the context finds a child;
* discounted probabilities and back-off weights as logarithms in 16 bits.

``EliasFano`` holds a monotone sequence: packed lower bits, upper bits in unary, and a count of ones for every 512 of
them from which select works. That is 2 + log2(largest / length) bits a value and an eighth.

Shards follow from the number of tokens. A word that is more frequent than a shard is long has its bigrams dealt over
several shards by the second word; how many distinct ones follow it is then added up. No table of words or
n-grams goes to the driver, only a row a shard and these words.

Smoothing: unseen words share the mass that once-seen words have (Good-Turing); higher orders use absolute
discounting, interpolated with the order below when a text is scored.

Defined cases: null text is the empty text, one end token; with nothing to learn from every score is 0; repeated
rows count as often as they occur; ties do not arise; texts are read whole; extra columns are ignored. Where the shared
folder is no local path, shards are fetched and the most recent ones held, up to ``HELD_BYTES``.
"""

from __future__ import annotations

import json
import os
import uuid
from collections import OrderedDict
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import coded_chunks, gathered, sliced, split_chunks, summed, trim
from evalengine.llm._common import checkpointed, fold_of, shared_dir, table, whole_text
from evalengine.llm._shingles import byte_hashes, mixed

DISCOUNT, TOKENS_A_SHARD, WINDOW = 0.6, 2_000_000, 1_000_000
END = byte_hashes(pa.array(["\0end of text"]))[0]
FLOOR, GRAIN = -20.0, 20.0 / 65535
HELD_BYTES, HELD_FILES = 256_000_000, 1024
SLICES = "docs binary, lost binary, held binary, starts binary, codes binary, words binary, seen binary, tokens long, learned long"
ONES, BYTES, HIGH = np.uint64(0xFFFFFFFFFFFFFFFF), np.uint64(0x0101010101010101), np.uint64(0x8080808080808080)
U = [np.uint64(i) for i in range(33)]
#: Of a byte b and r: where its r-th one stands, at 8 b + r.
IN_BYTE = np.array([([i for i in range(8) if b >> i & 1] + [0] * 8)[:8] for b in range(256)], np.int64).ravel()


# Files.


def _local(uri: str) -> str | None:
    return uri[7:] if uri.startswith("file://") else uri[5:] if uri.startswith("file:") else uri if "://" not in uri else None


def save(folder: str, name: str, arrays: dict[str, np.ndarray]) -> None:
    """Write arrays as one file; it appears whole or not at all, and a repeated task writes the same bytes."""
    head, at, parts = {}, 0, []
    for key, a in arrays.items():
        a = np.ascontiguousarray(a)
        head[key] = (a.dtype.str, len(a), at)
        at += (a.nbytes + 7) // 8 * 8
        parts.append(a.tobytes().ljust((a.nbytes + 7) // 8 * 8, b"\0"))
    text = json.dumps(head).encode()
    text = text.ljust((len(text) + 7) // 8 * 8)
    body = len(text).to_bytes(8, "little") + text + b"".join(parts)
    local = _local(folder)
    temporary = f"{name}.{uuid.uuid4().hex}.part"
    if local is not None:
        os.makedirs(local, exist_ok=True)
        with open(f"{local}/{temporary}", "wb") as f:
            f.write(body)
        os.replace(f"{local}/{temporary}", f"{local}/{name}")
    else:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(folder)
        store.create_dir(path, recursive=True)
        with store.open_output_stream(f"{path}/{temporary}") as f:
            f.write(body)
        store.move(f"{path}/{temporary}", f"{path}/{name}")


#: Open files of a worker, the most recent last; mapped pages are the system's to take back, fetched bytes are bounded.
_OPEN: OrderedDict[str, tuple[dict[str, np.ndarray], int]] = OrderedDict()


def load(folder: str, name: str) -> dict[str, np.ndarray]:
    """Arrays of a file, mapped into memory where the folder is a local path, fetched elsewhere."""
    key = f"{folder}/{name}"
    if key in _OPEN:
        _OPEN.move_to_end(key)
        return _OPEN[key][0]
    local, fetched = _local(folder), 0
    if local is not None:
        raw = np.asarray(np.memmap(f"{local}/{name}", np.uint8, "r"))
    else:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(folder)
        with store.open_input_file(f"{path}/{name}") as f:
            raw = np.frombuffer(f.read(), np.uint8)
        fetched = len(raw)
    n = int.from_bytes(raw[:8].tobytes(), "little")
    held = {k: raw[8 + n + at : 8 + n + at + size * np.dtype(kind).itemsize].view(kind) for k, (kind, size, at) in json.loads(raw[8 : 8 + n].tobytes()).items()}
    _OPEN[key] = held, fetched
    while len(_OPEN) > 1 and (len(_OPEN) > HELD_FILES or sum(x[1] for x in _OPEN.values()) > HELD_BYTES):
        _OPEN.popitem(last=False)
    return held


# Sequences.


class EliasFano:
    """A sorted sequence of unsigned integers, searched in whole arrays at once."""

    @staticmethod
    def arrays(name: str, values: np.ndarray) -> dict[str, np.ndarray]:
        v = values.astype(np.uint64)
        n, top = len(v), int(v[-1]) if len(v) else 0
        low = min(63, max(0, (top // n).bit_length() - 1)) if n else 0
        packed = np.zeros(n * low // 64 + 2, np.uint64)
        if n and low:
            bit = np.arange(n, dtype=np.int64) * low
            word, off = bit >> 6, (bit & 63).astype(np.uint64)
            part = v & np.uint64((1 << low) - 1)
            first = np.flatnonzero(np.concatenate(([True], np.diff(word) != 0)))
            packed[word[first]] = np.bitwise_or.reduceat(part << off, first)
            over = np.flatnonzero(off + np.uint64(low) > 64)
            packed[word[over] + 1] |= part[over] >> (np.uint64(64) - off[over])
        upper = (v >> np.uint64(low)).astype(np.int64)
        bits = np.zeros(-(-(n + (int(upper[-1]) if n else 0) + 2) // 512) * 512, bool)
        bits[upper + np.arange(n)] = True
        unary = np.packbits(bits, bitorder="little").view(np.uint64)
        ones = np.bitwise_count(unary).reshape(-1, 8).sum(axis=1, dtype=np.int64)
        before = np.concatenate(([0], np.cumsum(ones)))
        return {f"{name}.low": packed, f"{name}.high": unary, f"{name}.ones": before.astype(np.uint32 if n < 1 << 32 else np.uint64), f"{name}.shape": np.array([n, low], np.int64)}

    def __init__(self, held: dict[str, np.ndarray], name: str) -> None:
        self.packed, self.unary, self.ones = held[f"{name}.low"], held[f"{name}.high"], held[f"{name}.ones"]
        self.n, self.bits = (int(x) for x in held[f"{name}.shape"])
        self.mask = np.uint64((1 << self.bits) - 1)
        self.zeros = None

    def __len__(self) -> int:
        return self.n

    def _select(self, r: np.ndarray, one: bool) -> np.ndarray:
        """Where the r-th one (or zero) of the upper bits stands: by the counts of 512 bits, then words, bytes and a table."""
        if one:
            before = self.ones
        else:
            if self.zeros is None:
                self.zeros = np.arange(len(self.ones), dtype=np.int64) * 512 - self.ones.astype(np.int64)
            before = self.zeros
        block = np.searchsorted(before, r.astype(before.dtype), side="right") - 1
        r = r - before.take(block).astype(np.int64)
        words = self.unary.take((block * 8)[None, :] + np.arange(8)[:, None])
        if not one:
            words = words ^ ONES
        counts = np.cumsum(np.bitwise_count(words), axis=0, dtype=np.int16)
        k = (counts <= r.astype(np.int16)).sum(axis=0, dtype=np.int64)
        flat = k * len(r) + np.arange(len(r))
        r = (r - np.where(k > 0, counts.ravel().take(np.maximum(flat - len(r), 0)), 0)).astype(np.uint64)
        word = words.ravel().take(flat)
        s = word - (word >> U[1] & np.uint64(0x5555555555555555))
        s = (s & np.uint64(0x3333333333333333)) + (s >> U[2] & np.uint64(0x3333333333333333))
        s = (s + (s >> U[4]) & np.uint64(0x0F0F0F0F0F0F0F0F)) * BYTES  # in byte i: the ones up to it
        shift = np.bitwise_count((r * BYTES | HIGH) - s & HIGH).astype(np.uint64) << U[3]
        r = r - ((s << U[8]) >> shift & np.uint64(255))
        at = IN_BYTE.take(((word >> shift & np.uint64(255)) << U[3] | r).astype(np.int64))
        return block * 512 + k * 64 + shift.astype(np.int64) + at

    def _after(self, at: np.ndarray, r: np.ndarray) -> np.ndarray:
        """Where the one after the one at ``at``, which is number r, stands."""
        start = at + 1
        i, off = start >> 6, (start & 63).astype(np.uint64)
        w = self.unary.take(i, mode="clip") >> off | self.unary.take(i + 1, mode="clip") << U[1] << np.uint64(63) - off
        out = start + np.bitwise_count((w & (~w + U[1])) - U[1])
        far = np.flatnonzero((w == 0) | (i + 1 >= len(self.unary)))
        if len(far):
            out[far] = self._select(r[far] + 1, True)
        return out

    def _run_before(self, at: np.ndarray, zero: np.ndarray) -> np.ndarray:
        """How many ones stand right before the zero at ``at``, which is number ``zero``."""
        i, off = at >> 6, (at & 63).astype(np.uint64)
        below = np.where(i > 0, self.unary.take(np.maximum(i - 1, 0)), U[0]) >> off
        y = ~(self.unary.take(i) << U[1] << np.uint64(63) - off | below)
        # off 0 shifts a word out by 64 in two steps.
        far = np.flatnonzero(y == 0)
        for step in (1, 2, 4, 8, 16, 32):
            y |= y >> U[step]
        out = 64 - np.bitwise_count(y).astype(np.int64)
        if len(far):
            out[far] = at[far] - np.where(zero[far] > 0, self._select(np.maximum(zero[far] - 1, 0), False) + 1, 0)
        return out

    def _low(self, i: np.ndarray) -> np.ndarray:
        if not self.bits:
            return np.zeros(len(i), np.uint64)
        bit = i * self.bits
        word, off = bit >> 6, (bit & 63).astype(np.uint64)
        return (self.packed.take(word) >> off | self.packed.take(word + 1) << U[1] << np.uint64(63) - off) & self.mask

    def _value(self, i: np.ndarray, at: np.ndarray) -> np.ndarray:
        return (at - i).astype(np.uint64) << np.uint64(self.bits) | self._low(i)

    def at(self, i: np.ndarray) -> np.ndarray:
        i = i.astype(np.int64)
        return self._value(i, self._select(i, True))

    def range(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The values at i and at i + 1."""
        i = i.astype(np.int64)
        at = self._select(i, True)
        return self._value(i, at), self._value(i + 1, self._after(at, i))

    def find(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of the first value >= q, or the last index where there is none; whether q is there)."""
        if not self.n:
            return np.zeros(len(q), np.int64), np.zeros(len(q), bool)
        q = q.astype(np.uint64)
        upper, want = (q >> np.uint64(self.bits)).astype(np.int64), q & self.mask
        beyond = upper > int(self.ones.shape[0] - 1) * 512 - self.n - 1
        upper = np.where(beyond, 0, upper)
        ends = self._select(upper, False)
        stop = ends - upper
        lo, hi = stop - self._run_before(ends, upper), stop.copy()
        rows = np.flatnonzero(lo < hi)
        while len(rows):
            a, b = lo[rows], hi[rows]
            mid = (a + b) >> 1
            less = self._low(mid) < want[rows]
            a, b = np.where(less, mid + 1, a), np.where(less, b, mid)
            lo[rows], hi[rows] = a, b
            rows = rows[a < b]
        safe = np.minimum(lo, self.n - 1)
        hit = ~beyond & (lo < stop) & (self._low(safe) == want)
        return np.where(beyond, self.n - 1, safe), hit


def quantised(log10: np.ndarray) -> np.ndarray:
    return np.rint((np.clip(log10, FLOOR, 0) - FLOOR) / GRAIN).astype(np.uint16)


def restored(q: np.ndarray) -> np.ndarray:
    """Probabilities from their quantised logarithms."""
    return 10.0 ** (q.astype(np.float64) * GRAIN + FLOOR)


def paired(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct pairs (a, b >= -1) in order: their parts, and the pair of each place."""
    if not len(a):
        none = np.zeros(0, np.int64)
        return none, none, none
    if max(int(a.max()), int(b.max()) + 1) < 1 << 31:
        key, where = np.unique((a.astype(np.int64) << 32) | (b + 1).astype(np.int64), return_inverse=True)
        return key >> 32, (key & 0xFFFFFFFF) - 1, where
    key, where = np.unique(np.column_stack((a, b)).astype(np.int64), axis=0, return_inverse=True)
    return key[:, 0], key[:, 1], where.reshape(-1)


# Runs of numbers.


def _plane(values: np.ndarray) -> bytes:
    """64-bit numbers as planes of bytes, so that high bytes compress to nothing."""
    return values.astype(np.int64).view(np.uint8).reshape(-1, 8).T.tobytes()


def _run(*arrays: np.ndarray) -> bytes:
    raw = b"".join(_plane(a) for a in arrays)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _read_run(blob: bytes, arrays: int) -> list[np.ndarray]:
    size = int.from_bytes(blob[:8], "little")
    planes = np.frombuffer(pa.decompress(blob[8:], size, codec="zstd", asbytes=True), np.uint8).reshape(arrays, 8, -1)
    return [np.ascontiguousarray(p.T).view(np.int64).reshape(-1) for p in planes]


# Slices of tokens.


def token_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct token hashes, codes of all tokens with each text's end token, where each text starts)."""
    cut = coded_chunks(texts)
    found = split_chunks(pc.ascii_lower(cut.array), r"[\t-\r]+")
    distinct, of = np.unique(np.append(byte_hashes(found.pieces), END), return_inverse=True)
    at, ends = gathered(found.starts, cut.codes)
    body, starts = of[:-1][found.codes][at], ends[cut.starts]
    return distinct, np.insert(body, starts[1:], of[-1]), starts + np.arange(len(starts))


def tokenised(docs: DataFrame) -> DataFrame:
    """A row for each slice of texts (columns of ``SLICES``); ``docs`` has ``doc_id``, ``held_out`` and ``text``.

    A slice's words are numbered by their frequency in it, so that the numbers compress.
    """

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        words, codes, starts = token_hashes(batch.column(2))
        held = batch.column(1).to_numpy(zero_copy_only=False).astype(bool)
        order = np.argsort(-np.bincount(codes, minlength=len(words)), kind="stable")
        rank = np.empty(len(words), np.int64)
        rank[order] = np.arange(len(words))
        words, codes = words[order], rank[codes]
        own = np.repeat(~held, np.diff(starts))
        seen = np.bincount(codes[own], minlength=len(words))
        docs, lost = batch.column(0).fill_null(0).to_numpy(), batch.column(0).is_null().to_numpy(zero_copy_only=False)
        blobs = (docs, lost, held, starts, codes, words.view(np.int64), seen)
        yield pa.RecordBatch.from_arrays([*(pa.array([_run(b)], pa.binary()) for b in blobs), pa.array([len(codes)]), pa.array([int(own.sum())])], names=[c.split(" ")[0] for c in SLICES.split(", ")])

    read = docs.select(F.col("doc_id").cast("long"), F.coalesce("held_out", F.lit(False)).alias("held_out"), whole_text().alias("text"))
    return checkpointed(read.mapInArrow(sliced(run), SLICES))


def _over(rows: DataFrame, columns: list[str], run: Callable[..., Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """``run`` over the numbers in the columns of each slice, one slice at a time."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                yield from run(*(_read_run(c[i].as_py(), 1)[0] for c in batch.columns))
        trim()

    return rows.select(*columns).mapInArrow(task, schema)


# The trie.


@dataclass
class Trie:
    """``bases``: the first id of each word shard; ``hot``: by word id, over how many shards its bigrams are dealt, how often
    it occurs and how many distinct words follow it."""

    folder: str
    shards: int
    bases: list[int] = field(default_factory=list)
    hot: dict[int, list[int]] = field(default_factory=dict)
    tokens: int = 0
    types: int = 0
    once: int = 0

    def parts(self, shard: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        order = np.argsort(shard, kind="stable")
        edge = np.searchsorted(shard[order], np.arange(self.shards + 1))
        for s in np.flatnonzero(np.diff(edge)):
            yield int(s), order[edge[s] : edge[s + 1]]

    def word_shard(self, h: np.ndarray) -> np.ndarray:
        return (mixed(h) % np.uint64(self.shards)).astype(np.int64)

    def pair_shard(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        shard = mixed(first.astype(np.uint64) + np.uint64(1))
        if self.hot:
            ids = np.array(sorted(self.hot))
            at = np.minimum(np.searchsorted(ids, first), len(ids) - 1)
            wide = np.where(ids[at] == first, np.array([self.hot[i][0] for i in ids.tolist()])[at], 1).astype(np.uint64)
            shard = shard + mixed(second.astype(np.uint64) + np.uint64(7)) % wide
        return (shard % np.uint64(self.shards)).astype(np.int64)

    def words(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(id, count) of word hashes; id -1 and count 0 for unseen ones."""
        ids, counts = np.full(len(h), -1, np.int64), np.zeros(len(h), np.int64)
        for s, rows in self.parts(self.word_shard(h)) if self.bases else ():
            held = load(self.folder, f"words-{s}")
            i, hit = EliasFano(held, "words").find(h[rows])
            if len(held["count"]):
                ids[rows] = np.where(hit, i + self.bases[s], -1)
                counts[rows] = np.where(hit, held["count"][i], 0)
        return ids, counts

    def pairs(self, first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """For pairs of word ids (first >= 0): shard and place of the bigram (-1 if there is none), its discounted probability,
        and the weight of the order below after the first word (1 where nothing follows it)."""
        shard, place = self.pair_shard(first, second), np.full(len(first), -1, np.int64)
        prob, back = np.zeros(len(first)), np.ones(len(first))
        for s, rows in self.parts(shard):
            held = load(self.folder, f"grams-{s}")
            contexts, begin, second_ids = (EliasFano(held, x) for x in ("contexts", "begin", "second"))
            # Pairs of one first word come in a row: its context is looked up once.
            own, of = _in_a_row(first[rows])
            r, there = contexts.find(first[rows[own]])
            own_back = np.ones(len(own))
            own_back[there] = restored(held["back2"][r[there]])
            back[rows] = own_back[of]
            at = np.flatnonzero(there[of])
            if not len(at):
                continue
            i, hit = _child(begin, second_ids, r[there], (np.cumsum(there) - 1)[of[at]], second[rows[at]])
            place[rows[at]] = np.where(hit, i, -1)
            prob[rows[at]] = np.where(hit, restored(held["prob2"][i]), 0)
        for word, (_, count, followers) in self.hot.items():
            back[first == word] = max(DISCOUNT * followers / max(count, 1), 1e-9)
        return shard, place, prob, back

    def thirds(self, shard: np.ndarray, place: np.ndarray, third: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For bigrams by shard and place (>= 0) and word ids: the trigram's discounted probability and the weight of the order below."""
        prob, back = np.zeros(len(place)), np.ones(len(place))
        for s, rows in self.parts(shard):
            held = load(self.folder, f"grams-{s}")
            own, of = _in_a_row(place[rows])
            i, hit = _child(EliasFano(held, "follow"), EliasFano(held, "third"), place[rows[own]], of, third[rows])
            back[rows] = restored(held["back3"][place[rows[own]]])[of]
            if len(held["prob3"]):
                prob[rows] = np.where(hit, restored(held["prob3"][i]), 0)
        return prob, back

    def word_probabilities(self, counts: np.ndarray) -> np.ndarray:
        new = min(0.5, max(self.once, 1) / max(self.tokens, 1))
        return np.where(counts > 0, counts / max(self.tokens, 1) * (1 - new), new)


def _in_a_row(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(where each run of equal values begins, the run of each place)."""
    fresh = np.concatenate(([True], values[1:] != values[:-1]))[: len(values)]
    return np.flatnonzero(fresh), np.cumsum(fresh) - 1


def _child(begin: EliasFano, values: EliasFano, r: np.ndarray, of: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place of each ``word`` among the children of its range r[of], whether it is there)."""
    if not len(values):
        return np.zeros(len(of), np.int64), np.zeros(len(of), bool)
    b, e = (x.astype(np.int64) for x in begin.range(r))
    before = np.where(b > 0, values.at(np.maximum(b - 1, 0)).astype(np.int64) + 1, 0)
    i, hit = values.find(before[of] + np.maximum(word, 0))
    return i, hit & (word >= 0) & (i >= b[of]) & (i < e[of])


def _ranges(begin: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Word ids in ranges, raised so that the whole sequence ascends."""
    if not len(words):
        return words
    size = np.diff(begin)
    last = np.zeros(len(size), np.int64)
    last[size > 0] = words[begin[1:][size > 0] - 1] + 1
    return words + np.repeat(np.concatenate(([0], np.cumsum(last)[:-1])), size)


def _merged(runs: DataFrame, build: Callable[[int, list[bytes]], tuple]) -> list:
    """Hand each shard's runs to ``build(shard, blobs)``, one shard in memory at a time; its row goes to the driver."""

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, blobs, rows = None, [], []
        for batch in batches:
            for shard, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if shard != held and held is not None:
                    rows.append((held, *build(held, blobs)))
                    blobs = []
                held = shard
                blobs.append(blob)
        if held is not None:
            rows.append((held, *build(held, blobs)))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())), strict=True)], names=["shard", "nodes", "once", "hot", "numbers"])
        trim()

    found = runs.repartition("shard").sortWithinPartitions("shard").mapInArrow(reduce, "shard int, nodes long, once long, hot array<long>, numbers array<long>").collect()
    # The shuffle's files go when the driver's JVM finds that nothing refers to it any more.
    runs.sparkSession.sparkContext._jvm.System.gc()
    return found


def _sent(trie: Trie, shard: np.ndarray, *arrays: np.ndarray) -> Iterator[pa.RecordBatch]:
    """One run for each shard, in the order of the arrays; each in a batch of its own."""
    for s, rows in trie.parts(shard):
        yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([_run(*(a[rows] for a in arrays))], pa.binary())], names=["shard", "run"])


def learn(slices: DataFrame, tokens_a_shard: int = TOKENS_A_SHARD) -> Trie:
    """Build the trie from the texts of ``tokenised`` documents that are not held out."""
    trie = Trie(shared_dir(slices.sparkSession), 1)
    trie.tokens = slices.agg(F.coalesce(F.sum("learned"), F.lit(0))).first()[0]
    trie.shards = max(16, -(-trie.tokens // tokens_a_shard))

    def word_runs(words: np.ndarray, seen: np.ndarray) -> Iterator[pa.RecordBatch]:
        h, n = words.view(np.uint64)[seen > 0], seen[seen > 0]
        yield from _sent(trie, trie.word_shard(h), h.view(np.int64), n)

    def word_level(shard: int, blobs: list[bytes]) -> tuple:
        keys, counts = (np.concatenate(x) for x in zip(*(_read_run(b, 2) for b in blobs), strict=True))
        keys, where = np.unique(keys.view(np.uint64), return_inverse=True)
        counts = np.bincount(where, counts).astype(np.int64)
        save(trie.folder, f"words-{shard}", {**EliasFano.arrays("words", keys), "count": counts.astype(np.uint32 if counts.max() < 1 << 32 else np.int64)})
        hot = np.flatnonzero(counts > tokens_a_shard)
        return len(keys), int((counts == 1).sum()), hot.tolist(), counts[hot].tolist()

    rows = _merged(_over(slices, ["words", "seen"], word_runs, "shard int, run binary"), word_level)
    sizes = {r.shard: r.nodes for r in rows}
    trie.types, trie.once = sum(sizes.values()), sum(r.once for r in rows)
    none = np.zeros(0, np.uint64)
    for s in set(range(trie.shards)) - set(sizes):
        save(trie.folder, f"words-{s}", {**EliasFano.arrays("words", none), "count": none})
    trie.bases = np.concatenate(([0], np.cumsum([sizes.get(s, 0) for s in range(trie.shards)])))[:-1].tolist()
    trie.hot = {trie.bases[r.shard] + i: [-(-2 * c // tokens_a_shard), c, 0] for r in rows for i, c in zip(r.hot, r.numbers, strict=True)}
    rows = _merged(_over(slices, ["held", "starts", "codes", "words"], _gram_runs(trie), "shard int, run binary"), _gram_level(trie))
    for r in rows:
        for word, followers in zip(r.hot, r.numbers, strict=True):
            trie.hot[word][2] += followers
    for s in set(range(trie.shards)) - {r.shard for r in rows}:
        save(trie.folder, f"grams-{s}", _level(none.astype(np.int64), none.astype(np.int64), none.astype(np.int64), none.astype(np.int64), trie)[0])
    return trie


def _gram_runs(trie: Trie):
    def runs(held: np.ndarray, starts: np.ndarray, codes: np.ndarray, words: np.ndarray) -> Iterator[pa.RecordBatch]:
        ids, _ = trie.words(words.view(np.uint64))
        last = np.zeros(len(codes) + 2, bool)
        last[starts[1:] - 1] = True
        use = np.flatnonzero(np.repeat(held == 0, np.diff(starts)) & ~last[:-2])
        for k in range(0, len(use), WINDOW):
            at = use[k : k + WINDOW]
            within = (codes[at], codes[at + 1], codes[np.minimum(at + 2, len(codes) - 1)])
            here = np.zeros(len(words), bool)
            for x in within:
                here[x] = True
            local = np.flatnonzero(here)
            order = np.argsort(ids[local], kind="stable")
            rank = np.empty(len(words), np.int64)
            rank[local[order]] = np.arange(len(local))
            a, b, c = (rank[x] for x in within)
            c = np.where(last[at + 1], 0, c + 1)
            bits = len(local).bit_length()
            key, times = np.unique(a << 2 * bits | b << bits | c, return_counts=True)
            of, m = ids[local][order], (1 << bits) - 1
            first, second, third = of[key >> 2 * bits], of[key >> bits & m], np.append(-1, of)[key & m]
            yield from _sent(trie, trie.pair_shard(first, second), first, second, third + 1, times)

    return runs


def _level(first: np.ndarray, second: np.ndarray, third: np.ndarray, times: np.ndarray, trie: Trie) -> tuple[dict[str, np.ndarray], int, list[int], list[int]]:
    """Arrays of a shard from its n-grams and counts; third -1: no third word. And the followers of hot words in it."""
    one, two, pair = paired(first, second)
    count2 = np.bincount(pair, times, len(one))
    of, three, gram = paired(pair, third)
    count3 = np.bincount(gram, times, len(of))
    of, three, count3 = of[three >= 0], three[three >= 0], count3[three >= 0]
    owners, begin = np.unique(one, return_index=True)
    begin = np.append(begin, len(one))
    owner = np.repeat(np.arange(len(owners)), np.diff(begin))
    total = np.bincount(owner, count2, len(owners))
    spread = np.diff(begin)
    for word, (_, count, _) in trie.hot.items():
        total[owners == word] = count
    follow = np.searchsorted(of, np.arange(len(one) + 1))
    log = lambda x: quantised(np.log10(np.maximum(x, 1e-20)))
    total3 = np.bincount(of, count3, len(one))
    made = {
        **EliasFano.arrays("contexts", owners), **EliasFano.arrays("begin", begin), **EliasFano.arrays("second", _ranges(begin, two)),
        **EliasFano.arrays("follow", follow), **EliasFano.arrays("third", _ranges(follow, three)),
        "prob2": log((count2 - DISCOUNT) / total[owner]), "back2": log(DISCOUNT * spread / np.maximum(total, 1)),
        "prob3": log((count3 - DISCOUNT) / total3[of]), "back3": log(np.where(total3 > 0, DISCOUNT * np.diff(follow) / np.maximum(total3, 1), 1)),
    }
    hot = [(int(w), int(n)) for w, n in zip(owners, spread, strict=True) if int(w) in trie.hot] if trie.hot else []
    return made, len(one) + len(three), [w for w, _ in hot], [n for _, n in hot]


def _gram_level(trie: Trie):
    def build(shard: int, blobs: list[bytes]) -> tuple:
        first, second, third, times = (np.concatenate(x) for x in zip(*(_read_run(b, 4) for b in blobs), strict=True))
        made, nodes, hot, followers = _level(first, second, third - 1, times, trie)
        save(trie.folder, f"grams-{shard}", made)
        return nodes, 0, hot, followers

    return build


def _logs(trie: Trie, codes: np.ndarray, starts: np.ndarray, ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """log10 probability of every token; each distinct bigram and trigram is searched once."""
    p = trie.word_probabilities(counts)[codes]
    first = np.zeros(len(codes), bool)
    first[starts[:-1]] = True
    at = np.flatnonzero(~first)
    at = at[ids[codes[at - 1]] >= 0]
    a, b, pair = paired(codes[at - 1].astype(np.int64), codes[at].astype(np.int64))
    shard, place, prob, back = trie.pairs(ids[a], ids[b])
    p[at] = prob[pair] + back[pair] * p[at]
    of = np.full(len(codes), -1, np.int64)
    of[at] = np.where(place[pair] >= 0, pair, -1)
    at = np.flatnonzero(~first)
    at = at[of[at - 1] >= 0]
    at = at[~first[at - 1]]
    a, b, gram = paired(of[at - 1], codes[at].astype(np.int64))
    prob, back = trie.thirds(shard[a], place[a], ids[b])
    p[at] = prob[gram] + back[gram] * p[at]
    return np.log10(p)


def score(slices: DataFrame, trie: Trie) -> DataFrame:
    """``doc_id``, ``held_out``, ``n_tokens``, ``n_known``, ``train_tokens``, ``base_score`` and ``score`` of every text of ``tokenised`` documents."""

    def run(docs: np.ndarray, lost: np.ndarray, held: np.ndarray, starts: np.ndarray, codes: np.ndarray, words: np.ndarray) -> Iterator[pa.RecordBatch]:
        ids, counts = trie.words(words.view(np.uint64))
        base = np.log10((counts + 0.5) / (trie.tokens + 0.5 * (trie.types + 1)))
        log = _logs(trie, codes, starts, ids, counts) if trie.tokens else np.zeros(len(codes))
        yield pa.RecordBatch.from_arrays([
            pa.array(docs, mask=lost > 0), pa.array(held > 0), pa.array(np.diff(starts)), pa.array(summed((counts > 0)[codes], starts)),
            pa.array(np.full(len(starts) - 1, trie.tokens, np.int64)), pa.array(summed(base[codes], starts)), pa.array(summed(log, starts)),
        ], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return _over(slices, ["docs", "lost", "held", "starts", "codes", "words"], run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op3_ngram_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    slices = tokenised(table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), (fold_of(5) == 1).alias("held_out"), "text"))
    return score(slices, learn(slices))
