"""Byte-level BPE: encode by folding ranked merges over the bytes of distinct words, decode by
concatenating binary pieces.

Two forms give the same ids:

* ``merge_words_native``: Spark higher-order functions only. ``aggregate`` folds the best-ranked merge
  into a struct of pieces and pair ranks; the rank map is one literal, an array of small maps indexed
  by crc32, because Spark searches a map linearly. Exact, but interpreted (see README for figures).
* ``encode``: the main path. Arrow batches of texts are cut at single spaces and dictionary-encoded, so that
  the pre-tokenizer and the merge fold run once per distinct piece of text, and everything per occurrence
  stays in Arrow kernels. One narrow stage, no shuffle, memory bounded by a batch and a bounded cache.

Cutting before a space is exact where the text before it does not end in white space: no match of the
pre-tokenizer then spans the cut. Texts with other spaces are split as a whole instead.

Defined cases: null text is the empty text (no tokens, hashes of the empty string); a word of any length
is merged exactly (a heap takes over for long words); repeated rows each give a row; an empty table gives
an empty result; extra input columns are ignored, null ids pass through.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import coded_chunks, small
from evalengine.llm._common import table, whole_text

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
LONG_WORD = 96
UNRANKED = 1 << 60
CACHE_WORDS = 500_000

#: Ids by word of a Python worker, kept from task to task, emptied when full; one map for each vocabulary.
_KNOWN: dict[str, dict[str, bytes]] = {}


def read_ranks(path: str) -> dict[bytes, int]:
    """Ranks by piece of a rank file: one base64 piece and its rank on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(p): int(r) for p, r in (line.split() for line in f if line.strip())}


def fold_merges(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one word: merge the adjacent pair of lowest rank, leftmost first, until none is ranked."""
    if word in ranks:
        return [ranks[word]]
    if len(word) > LONG_WORD:
        return _fold_long(word, ranks)
    get, cut = ranks.get, list(range(len(word) + 1))
    at = [get(word[i : i + 2], UNRANKED) for i in range(len(word) - 1)]
    while at and (best := min(at)) != UNRANKED:
        i = at.index(best)
        del at[i], cut[i + 1]
        if i < len(at):
            at[i] = get(word[cut[i] : cut[i + 2]], UNRANKED)
        if i:
            at[i - 1] = get(word[cut[i - 1] : cut[i + 1]], UNRANKED)
    return [ranks[word[i:j]] for i, j in zip(cut, cut[1:], strict=False)]


def _fold_long(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    n = len(word)
    end, nxt, prev = list(range(1, n + 1)), list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    alive = bytearray(b"\1" * n)
    while heap:
        _, i, stop = heapq.heappop(heap)
        if not alive[i] or nxt[i] >= n or end[nxt[i]] != stop or end[i] != nxt[i]:
            continue
        j = nxt[i]
        alive[j] = 0
        end[i] = end[j]
        nxt[i] = nxt[j]
        if nxt[j] < n:
            prev[nxt[j]] = i
        for a in (prev[i], i):
            if a >= 0 and nxt[a] < n and (r := ranks.get(word[a : end[nxt[a]]])) is not None:
                heapq.heappush(heap, (r, a, end[nxt[a]]))
    return [ranks[word[i : end[i]]] for i in range(n) if alive[i]]


def encode(df: DataFrame, ranks: dict[bytes, int], pattern: str, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Encode every whole text and decode it again.

    Returns the digest columns of ``SCHEMA``; with ``keep_ids`` also ``ids array<int>`` and ``decoded binary``.
    ``ranks`` is broadcast: its size is that of the vocabulary file, whatever the data.
    """
    shared = df.sparkSession.sparkContext.broadcast(ranks)
    key = hashlib.sha256(repr((pattern, sorted(ranks.items()))).encode()).hexdigest()
    schema = SCHEMA + (", ids array<int>, decoded binary" if keep_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import regex

        rank = shared.value
        piece = {r: p for p, r in rank.items()}
        split = regex.compile(pattern).findall
        known = _KNOWN.setdefault(key, {})

        def ids_of(text: str) -> list[int]:
            out: list[int] = []
            for w in split(text):
                got = known.get(w)
                if got is None:
                    got = known[w] = np.array(fold_merges(w.encode(), rank), np.uint32).tobytes()
                out += memoryview(got).cast("I")
            return out

        def entry(ids: list[int]) -> tuple[int, str, bytes]:
            return len(ids), " ".join(map(str, ids)), b"".join([piece[i] for i in ids])

        for batch in (part for whole in batches for part in small(whole)):
            if len(known) > CACHE_WORDS:
                known.clear()
            cut = coded_chunks(batch.column(1))
            entries = [entry(ids_of(" " + w)) for w in cut.chunks]
            first, into = np.unique(cut.codes[cut.starts[:-1]], return_inverse=True)
            codes = cut.codes.copy()
            codes[cut.starts[:-1]] = len(entries) + into
            entries += [entry(ids_of(cut.chunks[c])) for c in first]
            total = np.concatenate(([0], np.cumsum(np.array([e[0] for e in entries], np.int64)[codes])))
            counts = total[cut.starts[1:]] - total[cut.starts[:-1]]
            starts, codes = pa.array(cut.starts.astype(np.int32)), pa.array(codes)
            spelled = pc.binary_join(pa.ListArray.from_arrays(starts, pa.array([e[1] for e in entries], pa.string()).take(codes)), " ").to_pylist()
            back = pc.binary_join(pa.ListArray.from_arrays(starts, pa.array([e[2] for e in entries], pa.binary()).take(codes)), b"").to_pylist()
            for i in cut.odd():
                counts[i], spelled[i], back[i] = entry(ids_of(batch.column(1)[i].as_py()))
            columns = [batch.column(0), pa.array(counts), pa.array([hashlib.sha256(x.encode()).hexdigest() for x in spelled]), pa.array([hashlib.sha256(x).hexdigest() for x in back])]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if keep_ids:
                columns += [pa.array([[int(x) for x in t.split()] for t in spelled], pa.list_(pa.int32())), pa.array(back, pa.binary())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return df.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text")).mapInArrow(run, schema)


# The native form.


def _let(value: Column, body) -> Column:
    return F.get(F.transform(F.array(value), body), F.lit(0))


def merge_words_native(words: DataFrame, ranks: dict[bytes, int], word_col: str = "word", buckets: int = 16384) -> DataFrame:
    """``ids`` of each distinct word of a frame, by higher-order functions alone.

    Bytes are held as the 256 first code points, so that a piece is a string and a merge a ``concat``.
    """
    parted: list[dict[str, int]] = [{} for _ in range(buckets)]
    for piece, r in ranks.items():
        key = piece.decode("latin-1")
        parted[zlib.crc32(key.encode()) % buckets][key] = r
    literal = F.from_json(F.lit(json.dumps(parted)), "array<map<string,int>>")
    none = F.lit(1 << 30)
    as_bytes = F.decode(F.encode(F.col(word_col), "UTF-8"), "ISO-8859-1")

    def ids(rank_map: Column, word: Column) -> Column:
        def rank(s: Column) -> Column:
            return F.coalesce(F.try_element_at(F.get(rank_map, (F.crc32(s.cast("binary")) % buckets).cast("int")), s), none)

        def merged(st: Column, low: Column) -> Column:
            p, r = st["p"], st["r"]
            return _let(F.array_position(r, low).cast("int"), lambda i: _let(F.concat(F.get(p, i - 1), F.get(p, i)), lambda w: F.struct(
                F.concat(F.slice(p, F.lit(1), i - 1), F.array(w), F.slice(p, i + 2, F.size(p))).alias("p"),
                F.concat(
                    F.slice(r, F.lit(1), F.greatest(i - 2, F.lit(0))),
                    F.when(i > 1, F.array(rank(F.concat(F.get(p, i - 2), w)))).otherwise(F.array().cast("array<int>")),
                    F.array(F.when(i + 1 < F.size(p), rank(F.concat(w, F.get(p, i + 1)))).otherwise(none)),
                    F.slice(r, i + 2, F.size(r)),
                ).alias("r"),
            )))

        begin = _let(F.split(word, ""), lambda p: F.struct(p.alias("p"), F.transform(p, lambda x, i: F.when(i + 1 < F.size(p), rank(F.concat(x, F.get(p, i + 1)))).otherwise(none)).alias("r")))
        folded = F.aggregate(
            F.sequence(F.lit(1), F.length(word)), begin,
            lambda st, _: _let(F.array_min(st["r"]), lambda low: F.when(low == none, st).otherwise(merged(st, low))),
            lambda st: F.transform(st["p"], rank),
        )
        return F.when(F.length(word) == 0, F.array().cast("array<int>")).when(rank(word) < none, F.array(rank(word))).otherwise(folded)

    distinct = words.select(word_col).where(F.col(word_col).isNotNull()).distinct()
    return distinct.select(word_col, _let(literal, lambda m: _let(as_bytes, lambda w: ids(m, w))).alias("ids"))


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    ranks = read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    return encode(table(spark, sf_dir, "documents"), ranks, public_tokenizers.PATTERN)
