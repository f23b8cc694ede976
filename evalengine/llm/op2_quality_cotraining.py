"""Quality classification by co-training two views of a document.

One view reads the text's content (shape of its words, symbols, repetition), the other the page metadata
(source, language, length). Each round, each view labels those pool documents of which its calibrated
probability is most certain, and the *other* view learns from them. At the end both views are calibrated on
labelled rows held back from fitting, and their calibrated logits add up to the score.

Bounds, as parameters: ``max_labelled`` labelled rows and ``max_pool`` unlabelled rows, drawn by id hash,
reach the driver as feature vectors; scoring covers every document in one narrow Arrow step.

Defined cases: null text is the empty text; null metadata is a value of its own; without labels of both classes (an
empty table included) every document gets score 0.5 and is kept; repeated ids each give a row and a label counts once
for each distinct text under its id; documents of equal scores are taken in the order of their ids; extra columns pass
through, those named like a result are renamed to ``input_<name>``.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import appended, coded_chunks, summed
from evalengine.llm._common import clear_of, table
from evalengine.llm._logit import Logit, fit_logit, sigmoid

SOURCES, LANGS = 32, 8


def shapes(chunks: pa.Array) -> np.ndarray:
    """Counts of kinds of characters in each distinct chunk, and what follows from them."""
    times = lambda pattern: pc.count_substring_regex(chunks, pattern).to_numpy(zero_copy_only=False).astype(np.float64)
    n = pc.utf8_length(chunks).to_numpy(zero_copy_only=False).astype(np.float64)
    letters, digits, upper, mild, lines, stops = map(times, (r"\p{L}", r"\p{Nd}", r"\p{Lu}", r"[.,;:'\"\-()?\n\t\r]", r"\n", r"\."))
    return np.column_stack((n, letters, digits, n - letters - digits - mild, upper, (letters > 1) & (upper == letters), lines, stops, n > 20, (n > 0) & (n < 3), (n > 0) & (letters == 0)))


def text_view(texts: pa.Array) -> np.ndarray:
    """One row of content features for each text; each distinct chunk is looked at once."""
    cut = coded_chunks(texts)
    shape = shapes(cut.array)
    n, letters, digits, symbols, upper, shouted, lines, stops, long, short, bare = (summed(shape[:, k][cut.codes], cut.starts) for k in range(11))
    words = np.diff(cut.starts).astype(np.float64)
    of = np.repeat(np.arange(len(words)), np.diff(cut.starts))
    pairs, times = np.unique(of << 32 | cut.codes, return_counts=True)
    owner = pairs >> 32
    distinct = np.bincount(owner, minlength=len(words)).astype(np.float64)
    top = np.zeros(len(words))
    np.maximum.at(top, owner, times)
    same = np.zeros(len(of))
    if len(of) > 1:
        same[1:] = (cut.codes[1:] == cut.codes[:-1]) & (of[1:] == of[:-1])
    chars, w = np.maximum(n, 1), np.maximum(words, 1)
    return np.column_stack((
        letters / chars, digits / chars, symbols / chars, upper / chars, shouted / w, lines / w, stops / w, long / w, short / w, bare / w,
        distinct / w, top / w, summed(same, cut.starts) / w, n / w, np.log1p(n), np.sqrt(symbols / chars), np.sqrt(upper / chars),
    ))


def metadata_view(batch: dict[str, list]) -> np.ndarray:
    out = np.zeros((len(batch["n_chars"]), SOURCES + LANGS + 3))
    for i, (source, lang, n) in enumerate(zip(batch["source"], batch["lang"], batch["n_chars"], strict=True)):
        out[i, zlib.crc32(f"s{source}".encode()) % SOURCES] = 1
        out[i, SOURCES + zlib.crc32(f"l{lang}".encode()) % LANGS] = 1
        out[i, -3:] = n is None, np.log1p(max(n or 0, 0)), np.log1p(max(n or 0, 0)) ** 2
    return out


@dataclass
class CoTrained:
    views: list[Logit]
    calibration: list[tuple[float, float]]
    prior: float
    exchanged: list[tuple[int, int]]

    def calibrated(self, k: int, x: np.ndarray) -> np.ndarray:
        a, b = self.calibration[k]
        return a * self.views[k].logits(x) + b

    def combined(self, x: list[np.ndarray]) -> np.ndarray:
        return sigmoid(self.calibrated(0, x[0]) + self.calibrated(1, x[1]) - self.prior)


def _platt(logits: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    m = fit_logit(logits[:, None], y, ridge=0.1)
    slope = max(0.0, m.weights[1] / m.scale[0])
    return float(slope), float(m.weights[0] - slope * m.mean[0] if slope else np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))


def co_train(x: list[np.ndarray], y: np.ndarray, held: np.ndarray, pool: list[np.ndarray], rounds: int = 4, take: int = 200, sure: float = 0.95) -> CoTrained:
    """``held`` marks labelled rows kept for calibration. Each view passes at most ``take`` pool rows of each class a round."""
    learn = [[v[~held] for v in x], [v[~held] for v in x]]
    given = [y[~held].astype(float), y[~held].astype(float)]
    free, exchanged = np.ones(len(pool[0]), bool), []
    for r in range(rounds + 1):
        views = [fit_logit(learn[k][k], given[k]) for k in (0, 1)]
        scale = [_platt(views[k].logits(x[k][held]), y[held].astype(float)) for k in (0, 1)]
        if r == rounds:
            break
        passed = []
        for k in (0, 1):
            p = sigmoid(scale[k][0] * views[k].logits(pool[k]) + scale[k][1])
            rows, labels = [], []
            for label, q in ((1.0, p), (0.0, 1 - p)):
                ranked = np.lexsort((np.arange(len(q)), -q))
                chosen = ranked[(q[ranked] >= sure) & free[ranked]][:take]
                rows.append(chosen)
                labels.append(np.full(len(chosen), label))
            rows, labels = np.concatenate(rows), np.concatenate(labels)
            free[rows] = False
            for j in (0, 1):
                learn[1 - k][j] = np.vstack((learn[1 - k][j], pool[j][rows]))
            given[1 - k] = np.concatenate((given[1 - k], labels))
            passed.append(len(rows))
        exchanged.append(tuple(passed))
        if not any(passed):
            break
    rate = float(np.clip(y.mean(), 1e-6, 1 - 1e-6))
    return CoTrained(views, scale, float(np.log(rate / (1 - rate))), exchanged)


def _viewed(df: DataFrame) -> DataFrame:
    at = {c: i for i, c in enumerate(df.columns)}

    def columns(batch: pa.RecordBatch) -> list:
        meta = metadata_view({c: batch.column(at[c]).to_pylist() for c in ("source", "lang", "n_chars")})
        return [pa.array(list(text_view(batch.column(at["text"]).fill_null("")))), pa.array(list(meta))]

    return appended(df, "text_view array<double>, metadata_view array<double>", columns).select("doc_id", "label", "text_view", "metadata_view")


def _bounded(rows: DataFrame, most: int) -> list:
    """The rows in the order of their ids; an id that is repeated without end cannot fill the driver."""
    return rows.orderBy("doc_id", "text_view").limit(most).collect()


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", max_labelled: int = 6000, max_pool: int = 4000) -> CoTrained | None:
    share = lambda n, most: int(min(1.0, most / max(1, n)) * (1 << 20))
    bucket = lambda salt: F.pmod(F.xxhash64(F.lit(salt), F.col("doc_id")), F.lit(1 << 20))
    known = labels.where(F.col(label_col).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(F.col(label_col).cast("int")).alias("label"))
    chosen = known.where(bucket(1) < share(known.count(), max_labelled))
    read = docs.select("doc_id", "text", "lang", "source", "n_chars")
    found = _bounded(_viewed(read.join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id", "text"])), 2 * max_labelled)
    y = np.array([int(r.label > 0) for r in found])
    if len(y) < 20 or len(set(y.tolist())) < 2:
        return None
    pool_rows = read.where(bucket(2) < share(docs.select("doc_id").count(), max_pool)).join(F.broadcast(chosen.select("doc_id")), "doc_id", "left_anti").withColumn("label", F.lit(None).cast("int"))
    pool = _bounded(_viewed(pool_rows), 2 * max_pool)
    held = np.array([zlib.crc32(f"held {r.doc_id}".encode()) % 3 == 0 for r in found])
    if len(set(y[held].tolist())) < 2 or len(set(y[~held].tolist())) < 2:
        held = np.arange(len(y)) % 2 == 0
    stack = lambda rows, c, wide: np.array([r[c] for r in rows], np.float64).reshape(-1, wide)
    wide = {"text_view": len(found[0]["text_view"]), "metadata_view": len(found[0]["metadata_view"])}
    return co_train([stack(found, c, w) for c, w in wide.items()], y, held, [stack(pool, c, w) for c, w in wide.items()])


def score(df: DataFrame, model: CoTrained | None, threshold: float = 0.5) -> DataFrame:
    """``df`` with ``text_score``, ``metadata_score``, ``quality_score`` and ``quality_keep``."""
    if model is None:
        half = F.lit(0.5)
        return clear_of(df, "text_score", "metadata_score", "quality_score", "quality_keep").withColumns({"text_score": half, "metadata_score": half, "quality_score": half, "quality_keep": F.lit(True)})
    shared = df.sparkSession.sparkContext.broadcast(model)
    at = {c: i for i, c in enumerate(df.columns)}

    def columns(batch: pa.RecordBatch) -> list:
        m = shared.value
        x = [text_view(batch.column(at["text"]).fill_null("")), metadata_view({c: batch.column(at[c]).to_pylist() for c in ("source", "lang", "n_chars")})]
        both = m.combined(x)
        return [pa.array(sigmoid(m.calibrated(0, x[0]))), pa.array(sigmoid(m.calibrated(1, x[1]))), pa.array(both), pa.array(both >= threshold)]

    return appended(df, "text_score double, metadata_score double, quality_score double, quality_keep boolean", columns)


def op2_quality_cotraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"))
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang", "source", "n_chars")
    return score(read, model).select("doc_id", "text_score", "metadata_score", "quality_score", "quality_keep")
