"""The corpus pipeline: five stages, each one corpus operator over all that the stage before it kept.

Stages take (spark, docs, sf_dir) and return a DataFrame; between stages the rows are written as Parquet and read
again. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine import importable
from evalengine.llm import op2_quality_cotraining, op5_curve_packing, op6_secret_scan, op9_language_id, op10_ngram_jaccard
from evalengine.llm._common import checkpointed, clear_of, fold_of, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without a language: null text, or no letter in it."""
    importable(spark)
    model = op9_language_id.fit(docs.where(fold_of(4) != 2))
    kept = op9_language_id.predict(clear_of(docs, "lang_pred", "score"), model)
    return kept.where(F.col("lang_pred") != op9_language_id.UNDETERMINED).select(*COLUMNS)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that the co-trained classifier rejects."""
    importable(spark)
    model = op2_quality_cotraining.fit(docs, table(spark, sf_dir, "labels"))
    return op2_quality_cotraining.score(docs.select(*COLUMNS), model).where("quality_keep").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document, the one of smallest id, of each group of near copies.

    Every row counts as a document of its own under a row number, so null and repeated ids lose no text and keep no copy;
    a null id comes after all others.
    """
    importable(spark)
    rows = checkpointed(docs.select(*COLUMNS, F.monotonically_increasing_id().alias("row")))
    classes = op10_ngram_jaccard.join(rows.select(F.col("row").alias("doc_id"), "text")).select(F.col("doc_id").alias("row"), "class_id")
    order = F.struct(F.col("doc_id").isNull().alias("lost"), "doc_id", "row")
    kept = rows.select("row", "doc_id").join(classes, "row").groupBy("class_id").agg(F.min(order).alias("first")).select(F.col("first.row").alias("row"))
    return rows.join(kept, "row", "left_semi").select(*COLUMNS)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets by a placeholder; every document stays."""
    importable(spark)
    return op6_secret_scan.redact(docs.select(*COLUMNS))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack all documents into sequences along the curve."""
    importable(spark)
    return op5_curve_packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language ID", language_id),
    ("quality classifier", quality),
    ("n-gram Jaccard join", near_duplicates),
    ("secret scans", secrets),
    ("packing", packing),
]

#: Models, sets of shingles and tokens are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written to the shared folder before the next reads them."""
    importable(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = checkpointed(docs)
    return docs
