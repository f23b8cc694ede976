"""Lexical metrics as Columns: everything stays in the plan, nothing is a Python function.

Edge rules: two empty texts agree (1), one empty text does not (0); null in, null out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PUNCTUATION = r"[!-/:-@\[-`{-~]"
SPACES = r"[ \t\n\r]+"
ARTICLES = r"\b(a|an|the)\b"


def normalised(text: Column, lower: bool = True, punctuation: bool = True, articles: bool = False, spaces: bool = True) -> Column:
    out = F.lower(text) if lower else text
    out = F.regexp_replace(out, PUNCTUATION, "") if punctuation else out
    out = F.regexp_replace(out, ARTICLES, " ") if articles else out
    return F.trim(F.regexp_replace(out, SPACES, " ")) if spaces else out


def tokens(text: Column) -> Column:
    """Normalised words."""
    return F.filter(F.split(normalised(text), " "), lambda w: w != "")


def exact_match(response: Column, reference: Column, normalise: bool = True, **options: bool) -> Column:
    a, b = (normalised(response, **options), normalised(reference, **options)) if normalise else (response, reference)
    return (a == b).cast("double")


def exact_match_any(response: Column, references: Column) -> Column:
    """The best over several references."""
    return F.exists(references, lambda r: normalised(r) == normalised(response)).cast("double")


def contains(response: Column, part: Column, case: bool = True) -> Column:
    return F.contains(response if case else F.lower(response), part if case else F.lower(part)).cast("double")


def _let(value: Column, body) -> Column:
    return F.get(F.transform(F.array(value), body), F.lit(0))


def numbered(a: Column) -> Column:
    """Each item with its occurrence number, so that bags can be handled as sets."""
    return _let(F.sort_array(a), lambda s: F.transform(s, lambda w, i: F.concat(w, F.lit("\x01"), (i + 1 - F.array_position(s, w)).cast("string"))))


def common(a: Column, b: Column) -> Column:
    """Size of the bag intersection of two arrays: the lesser count of each distinct item."""
    return F.size(F.array_intersect(numbered(a), numbered(b)))


def token_f1(a: Column, b: Column) -> Column:
    """F1 of two token arrays."""
    return F.when((F.size(a) == 0) & (F.size(b) == 0), 1.0).otherwise(2.0 * common(a, b) / (F.size(a) + F.size(b)))


def precision_recall(a: Column, b: Column) -> tuple[Column, Column]:
    n = common(a, b).cast("double")
    return F.try_divide(n, F.size(a)), F.try_divide(n, F.size(b))


def ngrams(a: Column, n: int) -> Column:
    """Runs of n words, each joined by a space."""
    return _let(a, lambda w: F.when(F.size(w) < n, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(w, i, n), " "))))


def bleu_parts(a: Column, b: Column, order: int = 4) -> list[tuple[Column, Column]]:
    """(clipped matches, n-grams) for each order."""
    return [(common(ngrams(a, n), ngrams(b, n)).cast("double"), F.greatest(F.size(a) - n + 1, F.lit(0)).cast("double")) for n in range(1, order + 1)]


def bleu_of(parts: list[tuple[Column, Column]], mine: Column, theirs: Column, smooth: str = "add_one") -> Column:
    """BLEU from matches, totals and lengths; works on one text's counts and on sums over a corpus."""
    logs = []
    for n, (m, t) in enumerate(parts):
        if smooth == "add_one" and n:
            logs.append(F.log((m + 1) / (t + 1)))
        elif smooth == "epsilon":
            logs.append(F.when(t > 0, F.log(F.greatest(m, F.lit(0.1)) / t)))
        else:
            logs.append(F.when((m > 0) & (t > 0), F.log(m / t)))
    penalty = F.when(mine > theirs, 1.0).otherwise(F.exp(1 - F.try_divide(theirs.cast("double"), mine)))
    return F.when(mine == 0, 0.0).otherwise(F.coalesce(penalty * F.exp(sum(logs[1:], logs[0]) / len(logs)), F.lit(0.0)))


def sentence_bleu(a: Column, b: Column, order: int = 4, smooth: str = "add_one") -> Column:
    return bleu_of(bleu_parts(a, b, order), F.size(a), F.size(b), smooth)


def corpus_bleu(df: DataFrame, a: Column, b: Column, order: int = 4) -> DataFrame:
    """One row: BLEU over the sums of all rows' counts."""
    parts = bleu_parts(a, b, order)
    named = {f"m{n}": m for n, (m, _) in enumerate(parts)} | {f"t{n}": t for n, (_, t) in enumerate(parts)} | {"c": F.size(a).cast("double"), "r": F.size(b).cast("double")}
    sums = df.select(*(v.alias(k) for k, v in named.items())).agg(*(F.sum(k).alias(k) for k in named))
    return sums.select(bleu_of([(F.col(f"m{n}"), F.col(f"t{n}")) for n in range(order)], F.col("c"), F.col("r"), "none").alias("corpus_bleu"), F.col("c").cast("long").alias("response_tokens"), F.col("r").cast("long").alias("reference_tokens"))


def common_subsequence(x: list, y: list) -> int:
    """Length of the longest common subsequence; one numpy step for each item of the shorter list."""
    if len(x) > len(y):
        x, y = y, x
    if not x:
        return 0
    codes = {w: i for i, w in enumerate(dict.fromkeys(y))}
    row = np.zeros(len(y) + 1, np.int64)
    other = np.array([codes[w] for w in y])
    for w in x:
        hit = row[:-1] + (other == codes.get(w, -1))
        row[1:] = np.maximum.accumulate(np.maximum(row[1:], hit))
    return int(row[-1])


def rouge_l(a: Column | str, b: Column | str) -> Column:
    """ROUGE-L F1 of two token arrays, in Arrow batches."""

    def scored(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for xs, ys in batches:
            out = []
            for x, y in zip(xs, ys, strict=True):
                if x is None or y is None:
                    out.append(None)
                elif not len(x) or not len(y):
                    out.append(float(len(x) == len(y)))
                else:
                    out.append(2 * common_subsequence(list(x), list(y)) / (len(x) + len(y)))
            yield pd.Series(out, dtype="float64")

    return F.pandas_udf(scored, "double")(a, b)


def rouge_l_native(a: Column, b: Column) -> Column:
    """The same by nested folds, for short texts: no Python worker."""
    first = F.array_repeat(F.lit(0), F.size(b) + 1)

    def row(before: Column, w: Column) -> Column:
        def cell(made: Column, j: Column) -> Column:
            here = F.when(F.get(b, j - 1) == w, F.get(before, j - 1) + 1).otherwise(F.greatest(F.get(before, j), F.element_at(made, -1)))
            return F.concat(made, F.array(here))

        return F.aggregate(F.sequence(F.lit(1), F.size(b)), F.array(F.lit(0)), cell)

    n = F.element_at(F.aggregate(a, first, row), -1).cast("double")
    return F.when((F.size(a) == 0) | (F.size(b) == 0), (F.size(a) == F.size(b)).cast("double")).otherwise(2 * n / (F.size(a) + F.size(b)))
