"""Queries of the corpus operators and, where SQL can express them, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from evalengine.llm.op1_byte_bpe import op1_byte_bpe
from evalengine.llm.op10_ngram_jaccard import op10_ngram_jaccard
from evalengine.llm.op2_quality_cotraining import op2_quality_cotraining
from evalengine.llm.op3_ngram_trie import op3_ngram_trie
from evalengine.llm.op4_html_extraction import op4_html_extraction
from evalengine.llm.op5_curve_packing import op5_curve_packing
from evalengine.llm.op6_secret_scan import op6_secret_scan
from evalengine.llm.op7_iblt_fingerprint import op7_iblt_fingerprint
from evalengine.llm.op8_collision_dedup import op8_collision_dedup
from evalengine.llm.op9_language_id import op9_language_id

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_byte_bpe, op2_quality_cotraining, op3_ngram_trie, op4_html_extraction, op5_curve_packing, op6_secret_scan, op7_iblt_fingerprint, op8_collision_dedup, op9_language_id, op10_ngram_jaccard)}


def oracle_sql() -> dict[str, str]:
    return {}
