"""Language identification, word first: known words score by per-language log frequency, unseen words back
off to the longest known character n-grams.

``fit`` learns from a bounded sample of labelled rows (about ``max_docs``, drawn by id hash, the same quota for each
language; a language below its quota is taken whole and leaves the rest to the others) and keeps every word of it, so
the model follows the sample and no language is crowded out. ``predict`` is one narrow Arrow step over whole texts.

Words are runs of letters (Unicode category L) in lower case, found by the same function when learning and when
predicting. The model is a few sorted arrays of hashes with log probabilities in whole millionths, so that sums are
exact and equal scores tie whatever the order of the words. All distinct words of a slice are searched at once.

Defined cases: null text, or a text without a letter, gives ``und`` with score 0; with no labelled rows (an empty table
included) every text gives ``und``; ties go to the language first in alphabetical order; repeated rows each give a
row, and count as often as they occur when learning; texts are read whole; extra columns pass through, those named
like a result are renamed to ``input_<name>``.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import Pieces, appended, coded_chunks, joined, sliced, split_chunks, summed
from evalengine.llm._common import fold_of, table
from evalengine.llm._shingles import mixed

UNDETERMINED = "und"
LONGEST, BLOCK = 4, 100_000
NOT_LETTERS = r"\P{L}+"
_STEP = np.uint64(0x9E3779B97F4A7C15)


def words_of(chunks: pa.Array) -> Pieces:
    """The lower-case words of distinct chunks."""
    return split_chunks(pc.utf8_lower(chunks), NOT_LETTERS)


@dataclass
class Spelled:
    """Framed words (a mark before, one after) as hashed code points in a row; word i takes ``begin[i]:begin[i+1]``."""

    points: np.ndarray
    begin: np.ndarray

    @staticmethod
    def of(words: pa.Array) -> Spelled:
        sizes = pc.utf8_length(words).to_numpy(zero_copy_only=False).astype(np.int64) + 2
        begin = np.concatenate(([0], np.cumsum(sizes)))
        points = np.frombuffer(joined(pc.binary_join_element_wise("^", words, "$", ""), "").encode("utf-32-le"), np.uint32)
        return Spelled(mixed((points.astype(np.uint64) + np.uint64(1)) * _STEP), begin)

    def words(self) -> np.ndarray:
        """A hash of each word."""
        if len(self.begin) == 1:
            return np.zeros(0, np.uint64)
        sizes = np.diff(self.begin)
        powers = np.multiply.accumulate(np.full(int(sizes.max()), _STEP))
        place = np.arange(len(self.points)) - np.repeat(self.begin[:-1], sizes)
        return mixed(np.add.reduceat(self.points * powers[place], self.begin[:-1]))

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of the n-grams that start at each place, and whether they end inside their word."""
        padded = np.concatenate((self.points, np.zeros(n, np.uint64)))
        h = np.full(len(self.points), n, np.uint64)
        for k in range(n):
            h = h * _STEP + padded[k : k + len(self.points)]
        room = np.repeat(self.begin[1:], np.diff(self.begin)) - np.arange(len(self.points))
        return mixed(h), room >= n


@dataclass
class Logs:
    """Sorted hashes, and for each the log probability under every language in millionths."""

    keys: np.ndarray
    values: np.ndarray

    @staticmethod
    def of(blocks: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]], n_langs: int) -> Logs:
        """From blocks of (hashes, languages, weights); no more than a block and the distinct hashes are held at once."""
        keys, m = np.zeros(0, np.uint64), np.zeros((0, n_langs))
        for more, langs, weights in blocks:
            found, at = np.unique(more, return_inverse=True)
            part = np.bincount(at * n_langs + langs, weights, len(found) * n_langs).reshape(-1, n_langs)
            both, at = np.unique(np.concatenate((keys, found)), return_inverse=True)
            total = np.zeros((len(both), n_langs))
            total[at[: len(keys)]] += m
            total[at[len(keys) :]] += part
            keys, m = both, total
        return Logs(keys, np.rint(1e6 * np.log((m + 0.5) / (m.sum(axis=0) + 0.5 * max(1, len(m))))).astype(np.int32))

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Places of the keys, -1 for those that are not there."""
        if not len(self.keys):
            return np.full(len(keys), -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1)


@dataclass
class Model:
    langs: list[str]
    words: Logs
    grams: list[Logs]
    floor: np.ndarray

    def scores(self, words: pa.Array) -> np.ndarray:
        """Per-language log probability of each word, in millionths."""
        spelled = Spelled.of(words)
        at = self.words.find(spelled.words())
        out = self.words.values[np.maximum(at, 0)].astype(np.int64) if len(self.words.keys) else np.zeros((len(at), len(self.langs)), np.int64)
        new = np.flatnonzero(at < 0)
        if len(new):
            part = Spelled.of(words.take(pa.array(new)))
            per = np.tile(self.floor.astype(np.int64), (len(part.points), 1))
            free = np.ones(len(part.points), bool)
            for n in range(LONGEST, 0, -1):
                keys, inside = part.grams(n)
                rows = np.flatnonzero(free & inside)
                got = self.grams[n - 1].find(keys[rows])
                rows, got = rows[got >= 0], got[got >= 0]
                per[rows] = self.grams[n - 1].values[got]
                free[rows] = False
            out[new] = summed(per, part.begin) // np.diff(part.begin)[:, None]
        return out


def quota(sizes: list[int], total: int) -> float:
    """The equal share of a language, so that all languages, each up to its size, give ``total`` documents."""
    left = float(total)
    for k, n in enumerate(sorted(sizes)):
        each = left / (len(sizes) - k)
        if n > each:
            return each
        left -= n
    return float(max(sizes, default=0))


def _counted(sample: DataFrame) -> pa.Table:
    """Counts of the words of each language (columns word, lang, count) in a frame of ``lang`` and ``text``."""

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        langs = batch.column(0).to_pylist()
        for lang in sorted(set(langs)):
            texts = batch.column(1).filter(pa.array([x == lang for x in langs]))
            cut = coded_chunks(texts.fill_null(""))
            found = words_of(cut.array)
            times = np.bincount(cut.codes, minlength=len(cut.array))
            counts = np.bincount(found.codes, np.repeat(times, np.diff(found.starts)), len(found.pieces)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([found.pieces, pa.array([lang] * len(counts), pa.string()), pa.array(counts)], names=["word", "lang", "n"])

    return sample.mapInArrow(sliced(run), "word string, lang string, n long").groupBy("word", "lang").agg(F.sum("n").alias("n")).toArrow()


def fit(labelled: DataFrame, max_docs: int = 6000, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id") -> Model:
    """Learn from rows whose language is not null: a hash sample of about ``max_docs`` of them, stratified by language."""
    rows = labelled.where(F.col(lang_col).isNotNull())
    sizes = {r.lang: r["count"] for r in rows.groupBy(F.col(lang_col).alias("lang")).count().collect()}
    none = Model([], Logs(np.zeros(0, np.uint64), np.zeros((0, 0), np.int32)), [], np.zeros(0, np.int64))
    if not sizes:
        return none
    each = quota(list(sizes.values()), max_docs)
    shares = F.create_map(*(F.lit(x) for lang, n in sizes.items() for x in (lang, math.ceil(min(1.0, each / n) * (1 << 20)))))
    sample = rows.where(F.pmod(F.xxhash64(F.col(id_col).cast("string")), F.lit(1 << 20)) < shares[F.col(lang_col)])
    counts = _counted(sample.select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text")))
    if not counts.num_rows:
        return none
    coded = counts.column("lang").combine_chunks().dictionary_encode()
    langs = sorted(coded.dictionary.to_pylist())
    of = np.array([langs.index(x) for x in coded.dictionary.to_pylist()])[np.asarray(coded.indices)]
    times = counts.column("n").to_numpy().astype(np.float64)
    words = counts.column("word").combine_chunks()

    def blocks(n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Hashes of the n-grams of the words, or of the words themselves for n = 0."""
        for k in range(0, len(words), BLOCK):
            spelled, lang, t = Spelled.of(words.slice(k, BLOCK)), of[k : k + BLOCK], times[k : k + BLOCK]
            if n:
                keys, inside = spelled.grams(n)
                size = np.diff(spelled.begin)
                yield keys[inside], np.repeat(lang, size)[inside], np.repeat(1 + np.log(t), size)[inside]
            else:
                yield spelled.words(), lang, t

    grams = [Logs.of(blocks(n), len(langs)) for n in range(1, LONGEST + 1)]
    mass = np.bincount(of, (1 + np.log(times)) * (pc.utf8_length(words).to_numpy(zero_copy_only=False) + 2), len(langs))
    floor = np.rint(1e6 * np.log(0.5 / (mass + 0.5 * max(1, len(grams[0].keys))))).astype(np.int64)
    return Model(langs, Logs.of(blocks(0), len(langs)), grams, floor)


def predict(df: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """``df`` with ``lang_pred`` and ``score`` (the posterior under equal priors, 0 to 1)."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    column = df.columns.index(text_col)

    def columns(batch: pa.RecordBatch) -> list:
        m: Model = shared.value
        cut = coded_chunks(batch.column(column).fill_null(""))
        found = words_of(cut.array)
        known = summed(np.diff(found.starts)[cut.codes], cut.starts) > 0
        if not m.langs or not known.any():
            return [pa.array([UNDETERMINED] * batch.num_rows), pa.array(np.zeros(batch.num_rows))]
        per_chunk = summed(m.scores(found.pieces)[found.codes], found.starts)
        totals = np.column_stack([summed(per_chunk[:, k][cut.codes], cut.starts) for k in range(len(m.langs))])
        best = totals.argmax(axis=1)
        odds = np.exp((totals - totals.max(axis=1, keepdims=True)) / 1e6)
        names = np.where(known, np.array(m.langs, object)[best], UNDETERMINED)
        return [pa.array(names, pa.string()), pa.array(np.where(known, 1 / odds.sum(axis=1), 0.0))]

    return appended(df, "lang_pred string, score double", columns)


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(docs.where(fold_of(4) != 2))
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold_of(4) == 2).alias("held_out"), "text")
    return predict(read, model).select("doc_id", "held_out", "lang_pred", "score")
