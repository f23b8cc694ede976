"""Byte-pair merges of many words at once, and the words of many texts at once, as array operations."""

from __future__ import annotations

import functools
import json
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from evalengine.llm._arrow import gathered, joined, strings
from evalengine.llm._shingles import mixed

# The word pattern of the vocabulary files that ``Tokens`` knows, and the characters (printable ASCII, line
# ends, Latin letters up to U+017F without the dotted capital I) on which all lower-casing and letter tables agree.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
PLAIN = r"^[\t\n\r\x21-\x7e\x{a1}-\x{12f}\x{131}-\x{17f}]*$"
WORD_END = "</w>"
LONG_WORD = 48
CACHE_WORDS = 1_500_000
GAP, LETTER, NUMBER, OTHER = range(4)
_UNRANKED = np.int32(2**31 - 1)
_P = np.uint64(0x9E3779B97F4A7C15)


def byte_letters() -> list[str]:
    """The character that stands for each byte in a byte-level vocabulary: printable Latin-1 for itself, the rest from U+0100 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in own]
    names = {b: chr(b) for b in own} | {b: chr(256 + k) for k, b in enumerate(rest)}
    return [names[b] for b in range(256)]


@functools.cache
def _kinds() -> np.ndarray:
    """The kind of each code point below U+0180."""
    of = {"L": LETTER, "N": NUMBER}
    return np.array([GAP if chr(c) in "\0\t\n\r " else of.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x180)], np.int8)


def word_bounds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of lower-cased plain UTF-8 text begin, and their lengths in bytes."""
    if not len(raw):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = _kinds()[np.minimum(raw, 127)]
    lead = np.flatnonzero(raw >= 0xC0)
    kind[lead] = kind[lead + 1] = _kinds()[(raw[lead].astype(np.int64) & 31) << 6 | raw[lead + 1] & 63]
    begin = np.ones(len(raw), bool)
    begin[1:] = (kind[1:] != kind[:-1]) | (kind[1:] != LETTER) & (kind[1:] != OTHER)
    begin[lead + 1] = False
    # A mark that stands alone before certain letters takes them with it.
    mark = np.flatnonzero((raw == ord("'")) & begin)
    padded = np.concatenate((raw, np.zeros(3, np.uint8)))
    first, second = padded[mark + 1], padded[mark + 2]
    one = np.isin(first, np.frombuffer(b"stmd", np.uint8))
    two = np.isin(first.astype(np.int64) << 8 | second, [int.from_bytes(x, "big") for x in (b"re", b"ve", b"ll")])
    for hit, n in ((mark[one], 1), (mark[two], 2)):
        begin[hit + 1] = False
        after = hit[hit + n + 1 < len(raw)] + n + 1
        begin[after[kind[after] == LETTER]] = True
    at = np.flatnonzero(begin)
    size = np.diff(np.append(at, len(raw)))
    full = kind[at] != GAP
    return at[full], size[full]


class Merges:
    """The merge table of a byte-level vocabulary with marked word ends."""

    def __init__(self, vocab: dict[str, int], merges: list) -> None:
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        letters = byte_letters()
        self.inner = np.array([vocab[x] for x in letters], np.int64)
        self.last = np.array([vocab[x + WORD_END] for x in letters], np.int64)
        keys = np.array([vocab[a] << 32 | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank = keys[order], order.astype(np.int32)
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)

    def ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        q = a << 32 | b
        at = np.minimum(np.searchsorted(self.keys, q), len(self.keys) - 1)
        return np.where(self.keys[at] == q, self.rank[at], _UNRANKED)

    def fold(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words of one length (a matrix of bytes): a matrix of as many columns, and how many of each row count.

        Each round joins, in every word that is not done, its leftmost pair of lowest rank.
        """
        n, wide = words.shape
        symbols, sizes = self.inner[words], np.full(n, wide)
        symbols[:, -1] = self.last[words[:, -1]]
        if wide == 1:
            return symbols, sizes
        ranked = np.full((n, wide), _UNRANKED)
        ranked[:, :-1] = self.ranks(symbols[:, :-1], symbols[:, 1:])
        out, rows, columns = symbols.copy(), np.arange(n), np.arange(wide)
        while len(rows):
            at = ranked.argmin(axis=1)
            best = np.take_along_axis(ranked, at[:, None], 1)[:, 0]
            done = best == _UNRANKED
            if done.any():
                out[rows[done]] = symbols[done]
                go = ~done
                rows, symbols, ranked, at, best = rows[go], symbols[go], ranked[go], at[go], best[go]
                if not len(rows):
                    break
            shift = np.minimum(columns[None, :] + (columns[None, :] > at[:, None]), wide - 1)
            symbols, ranked = np.take_along_axis(symbols, shift, 1), np.take_along_axis(ranked, shift, 1)
            i = np.arange(len(rows))
            symbols[i, at] = self.made[best]
            sizes[rows] -= 1
            size = sizes[rows]
            ranked[i, size - 1] = _UNRANKED
            right = at + 1 < size
            ranked[i[right], at[right]] = self.ranks(symbols[i[right], at[right]], symbols[i[right], at[right] + 1])
            ranked[i[~right], at[~right]] = _UNRANKED
            left = at > 0
            ranked[i[left], at[left] - 1] = self.ranks(symbols[i[left], at[left] - 1], symbols[i[left], at[left]])
        return out, sizes


class Tokens:
    """Ids of chunks under a tokenizer file, equal to the library's with ``add_special_tokens=False``.

    White space separates words for this tokenizer whatever surrounds it, so chunks are tokenized apart. The words of plain
    chunks go through the merges together, each distinct word once. Chunks with other characters or with a special token's
    text go through the library as they are, and so do all chunks if the file's normalizer or pattern is another one.
    Known words are held as sorted arrays, emptied beyond ``CACHE_WORDS`` words and at the end of a task.
    """

    def __init__(self, path: str) -> None:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.model = self.whole.model
        with open(path, encoding="utf-8") as f:
            read = json.load(f)
        steps = [x["type"] for x in (read["normalizer"] or {}).get("normalizers", [])]
        cuts = (read["pre_tokenizer"] or {}).get("pretokenizers", [])
        self.quick = steps == ["NFC", "Replace", "Lowercase"] and [c["type"] for c in cuts] == ["Split", "ByteLevel"] and cuts[0]["pattern"] == {"Regex": WORD_PATTERN} and read["model"].get("end_of_word_suffix") == WORD_END
        self.special = [t["content"] for t in read["added_tokens"]]
        self.merges = Merges(read["model"]["vocab"], read["model"]["merges"]) if self.quick else None
        self.letters = {b: x for b, x in enumerate(byte_letters())}
        self.forget()

    def forget(self) -> None:
        self.keys, self.starts, self.ids = np.zeros(0, np.uint64), np.zeros(1, np.int64), np.zeros(0, np.uint32)

    def _fold(self, raw: np.ndarray, at: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words of ``raw`` at the given places in a row, and where each word's ids start."""
        counts = np.zeros(len(at), np.int64)
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        for wide in np.unique(size):
            rows = np.flatnonzero(size == wide)
            if wide <= LONG_WORD:
                ids, n = self.merges.fold(raw[at[rows][:, None] + np.arange(wide)])
                counts[rows] = n
                parts.append((rows, ids[np.arange(wide)[None, :] < n[:, None]]))
            else:
                found = [[t.id for t in self.model.tokenize(raw[a : a + wide].tobytes().decode("latin-1").translate(self.letters))] for a in at[rows].tolist()]
                counts[rows] = [len(f) for f in found]
                parts.append((rows, np.array([i for f in found for i in f], np.int64)))
        starts = np.concatenate(([0], np.cumsum(counts)))
        ids = np.zeros(starts[-1], np.uint32)
        for rows, found in parts:
            ids[gathered(starts, rows)[0]] = found
        return ids, starts

    def _known(self, raw: np.ndarray, at: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids and their starts, and the entry of each word of ``raw``; new words join the entries."""
        if not len(at):
            return self.ids, self.starts, np.zeros(0, np.int64)
        powers = np.multiply.accumulate(np.full(int(size.max()), _P))
        ends = np.concatenate(([0], np.cumsum(size)))
        place = np.repeat(at - ends[:-1], size) + np.arange(ends[-1])
        inner = np.arange(len(place)) - np.repeat(ends[:-1], size)
        hashes = mixed(np.add.reduceat(mixed(raw[place].astype(np.uint64) + np.uint64(1)) * powers[inner], ends[:-1]) + size.astype(np.uint64))
        distinct, first, entry = np.unique(hashes, return_index=True, return_inverse=True)
        if len(self.keys) > CACHE_WORDS:
            self.forget()
        there = np.searchsorted(self.keys, distinct)
        fresh = np.flatnonzero(np.append(self.keys, 0)[there] != distinct if len(self.keys) else np.ones(len(distinct), bool))
        if len(fresh):
            ids, starts = self._fold(raw, at[first[fresh]], size[first[fresh]])
            keys = np.concatenate((self.keys, distinct[fresh]))
            order = np.argsort(keys, kind="stable")
            begin = np.concatenate((self.starts, self.starts[-1] + starts[1:]))
            taken, ends = gathered(begin, order)
            self.keys, self.starts, self.ids = keys[order], ends, np.concatenate((self.ids, ids))[taken]
        return self.ids, self.starts, np.searchsorted(self.keys, distinct)[entry]

    def of(self, chunks: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all chunks in a row, and where each chunk's ids start."""
        plain = pc.match_substring_regex(chunks, PLAIN) if self.quick else pa.array(np.zeros(len(chunks), bool))
        for text in self.special:
            plain = pc.and_not(plain, pc.match_substring(chunks, text))
        odd = np.flatnonzero(~plain.to_numpy(zero_copy_only=False))
        raw = np.frombuffer(joined(pc.utf8_lower(pc.if_else(plain, chunks, "")), "\0").encode(), np.uint8)
        at, size = word_bounds(raw)
        ids, starts, entry = self._known(raw, at, size)
        chunk = np.cumsum(raw == 0)[at] if len(at) else at
        taken, ends = gathered(starts, entry)
        ids, starts = ids[taken], ends[np.concatenate(([0], np.cumsum(np.bincount(chunk, minlength=len(chunks)))))]
        if len(odd):
            rest = [np.array(e.ids, np.uint32) for e in self.whole.encode_batch_fast(strings(chunks.take(pa.array(odd))), add_special_tokens=False)]
            sizes = np.zeros(len(chunks), np.int64)
            sizes[odd] = [len(r) for r in rest]
            ids = np.insert(ids, np.repeat(starts[odd], sizes[odd]), np.concatenate(rest))
            starts = starts + np.concatenate(([0], np.cumsum(sizes)))
        return ids, starts


@functools.cache
def tokens(path: str) -> Tokens:
    """One for each worker: its vocabulary has a fixed size, its known words leave with ``forget``."""
    return Tokens(path)
