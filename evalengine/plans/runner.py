"""An evaluation from examples to metric values: render, infer through the cache, score in one projection, aggregate."""

from __future__ import annotations

import math
import uuid
from datetime import UTC, datetime

from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F

from evalengine.functions import lexical, semantic
from evalengine.functions.templating import render
from evalengine.operators import intervals, judge
from evalengine.operators.cache import ResponseCache
from evalengine.operators.inference import CallPolicy, call_model, distinct_requests, keyed
from evalengine.plans.spec import EvaluationSpec, MetricSpec
from evalengine.sources.staging import staged

VALUES = "metric string, kind string, value double, ci_lo double, ci_hi double, n long, n_missing long, ci_method string, level double"

METRICS = {
    "exact_match": ("binary", lambda r, g, o: lexical.exact_match(r, g, **o)),
    "contains": ("binary", lambda r, g, o: lexical.contains(r, g, **o)),
    "token_f1": ("continuous", lambda r, g, o: lexical.token_f1(lexical.tokens(r), lexical.tokens(g))),
    "bleu": ("continuous", lambda r, g, o: lexical.sentence_bleu(lexical.tokens(r), lexical.tokens(g), **o)),
    "rouge_l": ("continuous", lambda r, g, o: lexical.rouge_l(lexical.tokens(r), lexical.tokens(g))),
    "token_match": ("continuous", lambda r, g, o: semantic.token_match(lexical.tokens(r), lexical.tokens(g), **o)),
    "embedding_cosine": ("continuous", lambda r, g, o: semantic.sentence_cosine(lexical.tokens(r), lexical.tokens(g), **o)),
    "judge": ("ordinal", None),
}


def register(name: str, kind: str, metric) -> None:
    """Add a metric: ``metric(response, reference, options) -> Column``."""
    METRICS[name] = (kind, metric)


def suggest(df: DataFrame, reference: str = "reference", contexts: str | None = None) -> list[tuple[str, str]]:
    """(metric, reason) by which columns there are and how long references run."""
    out = [("judge", "open answers")]
    if reference in df.columns:
        words = df.agg(F.avg(F.size(F.split(reference, " "))).alias("w")).first().w or 0
        out = [("exact_match", "short references"), ("token_f1", "short references")] if words <= 8 else [("rouge_l", "long references"), ("bleu", "long references"), *out]
    if contexts and contexts in df.columns:
        out += [("faithfulness", "contexts are there"), ("context_precision", "contexts are there")]
    return out


def score_wide(df: DataFrame, metrics: tuple[MetricSpec, ...], response: str = "response", reference: str = "reference") -> DataFrame:
    """All metrics but judged ones in one projection over one scan."""
    r, g = F.col(response), F.col(reference)
    made: dict[str, Column] = {m.name: METRICS[m.name][1](r, g, m.options) for m in metrics if m.family != "judge"}
    return df.select("*", *(c.alias(n) for n, c in made.items()))


def skewness(point: Row) -> float:
    """Skewness from the power sums of ``intervals.moments``."""
    if not point.n:
        return 0.0
    m2 = point.s2 - point.n * point.mean**2
    m3 = point.s3 - 3 * point.mean * point.s2 + 2 * point.n * point.mean**3
    return math.sqrt(point.n) * m3 / m2**1.5 if m2 > 1e-12 * point.s2 else 0.0


def summarise(scores: DataFrame, spec: EvaluationSpec) -> DataFrame:
    """One row for each metric: value, interval, n. One aggregate gives the moments of all metrics, from which methods are chosen."""
    s, out = spec.statistics, []
    points = intervals.moments_wide(scores, [m.name for m in spec.metrics])
    for m in spec.metrics:
        kind, point = METRICS[m.name][0], points[m.name]
        method, _ = intervals.choose(kind, point.n, skewness(point), s.interval)
        if point.n == 0:
            row = scores.sparkSession.createDataFrame([(None, None, None)], "value double, ci_lo double, ci_hi double")
        elif method in ("wilson", "wald"):
            row = intervals.proportion(scores, m.name, getattr(intervals, method), s.level)
        elif method == "t":
            row = intervals.t_mean(scores, m.name, s.level)
        else:
            row = (intervals.bca if method == "bca" else intervals.percentile)(scores, m.name, s.iterations, s.level, spec.seed, s.engine)
        out.append(row.select(F.lit(m.name).alias("metric"), F.lit(kind).alias("kind"), "value", "ci_lo", "ci_hi", F.lit(point.n).cast("long").alias("n"), F.lit(point.n_missing).cast("long").alias("n_missing"), F.lit(method).alias("ci_method"), F.lit(s.level).alias("level")))
    total = out[0]
    for row in out[1:]:
        total = total.unionByName(row)
    return total


def summarise_segments(scores: DataFrame, spec: EvaluationSpec) -> DataFrame:
    """A row for each metric and segment of ``statistics.segments``: Wilson for binary metrics, t for the others, every row
    of one metric from one aggregate."""
    by, total = list(spec.statistics.segments), None
    for m in spec.metrics:
        kind = METRICS[m.name][0]
        row = intervals.proportion(scores, m.name, intervals.wilson, spec.statistics.level, by) if kind == "binary" else intervals.t_mean(scores, m.name, spec.statistics.level, by)
        part = row.select(F.lit(m.name).alias("metric"), F.lit(kind).alias("kind"), *by, "n", "value", "ci_lo", "ci_hi", F.lit("wilson" if kind == "binary" else "t").alias("ci_method"))
        total = part if total is None else total.unionByName(part)
    return total


def answered(rows: DataFrame, model: dict, spec: EvaluationSpec, at: datetime | None = None) -> tuple[DataFrame, dict[str, int]]:
    """Keyed rows with ``response_text`` and ``error``: one call for each distinct request, through the cache if the spec has one."""
    c = spec.calls
    requests = distinct_requests(rows)
    policy = CallPolicy(c.batch_size, c.rpm, c.tpm, c.lanes, c.slots, c.initial_fill)
    call = lambda r: r.join(call_model(r, model, policy).drop("attempts"), "cache_key")
    if c.cache_path:
        responses, counts = ResponseCache(rows.sparkSession, c.cache_path).resolve(requests, c.cache_policy, call, at or datetime.now(UTC).replace(tzinfo=None), c.ttl_days)
    else:
        responses, counts = staged(call(requests)), {}
    return rows.join(responses.select("cache_key", "response_text", "error"), "cache_key", "left"), counts


def respond(df: DataFrame, spec: EvaluationSpec, at: datetime | None = None) -> tuple[DataFrame, dict[str, int]]:
    """Rows with ``response`` and ``error`` (of a failed call); and the run's counts."""
    model = {"provider": spec.responder.provider, "model": spec.responder.model, "temperature": spec.responder.temperature, "max_tokens": spec.responder.max_tokens, **spec.responder.params}
    named = df.withColumnRenamed(spec.data.reference_col, "reference") if spec.data.reference_col != "reference" else df
    rows, counts = answered(keyed(render(named, spec.data.template), model), model, spec, at)
    return rows.withColumnRenamed("response_text", "response"), counts


def grade(df: DataFrame, spec: EvaluationSpec, options: dict) -> DataFrame:
    """Verdicts of a grader on ``response``: a row for each example and criterion with ``raw``, ``score`` (null if the verdict holds
    none) and ``error``. Prompts go through the same distinct, limited, cached inference as any others."""
    low, high = options.get("scale", (1, 5))
    prompts = judge.grade_prompts(df, options.get("rubric", "Grade the answer."), list(options.get("criteria", ["helpfulness"])), (low, high))
    model = {"provider": options.get("provider", "simulated-judge"), "model": options.get("model", "judge-a"), "temperature": 0.0, "max_tokens": 256}
    rows, _ = answered(keyed(prompts, model), model, spec)
    return rows.select(spec.data.id_col, "criterion", F.col("response_text").alias("raw"), judge.parse_score(F.col("response_text"), low, high).alias("score"), "error")


def evaluate(df: DataFrame, spec: EvaluationSpec, unparsed_path: str | None = None) -> DataFrame:
    """Metric values of a run. Judged metrics are the mean score over their criteria; verdicts without a score are
    missing values, and go to ``unparsed_path`` if it is given."""
    rows, _ = respond(df, spec)
    scores = score_wide(rows, spec.metrics)
    for m in (m for m in spec.metrics if m.family == "judge"):
        asked = rows.select(spec.data.id_col, "reference", F.col("response"), *(c for c in ("instruction",) if c in rows.columns))
        verdicts = staged(grade(asked if "instruction" in asked.columns else asked.withColumn("instruction", F.lit("")), spec, m.options))
        if unparsed_path:
            judge.unparsed(verdicts).write.mode("append").parquet(unparsed_path)
        scores = scores.join(verdicts.groupBy(spec.data.id_col).agg(F.avg("score").alias(m.name)), spec.data.id_col, "left")
    scores = staged(scores.select(spec.data.id_col, *spec.statistics.segments, *(m.name for m in spec.metrics)))
    return staged(summarise_segments(scores, spec) if spec.statistics.segments else summarise(scores, spec))


def registered(spec: EvaluationSpec, values: DataFrame, path: str) -> str:
    """Store the specification beside the results; returns the run's id."""
    run = uuid.uuid4().hex
    rows = [tuple(r) for r in values.collect()]
    record = values.sparkSession.createDataFrame([(run, spec.fingerprint(), spec.to_json(), [dict(zip(values.columns, r, strict=True)) for r in rows])], f"run_id string, fingerprint string, spec_json string, metrics array<struct<{', '.join(x.replace(' ', ':', 1) for x in VALUES.split(', '))}>>")
    record.write.mode("append").parquet(path)
    return run


__all__ = ["METRICS", "answered", "evaluate", "grade", "register", "registered", "respond", "score_wide", "suggest", "summarise", "summarise_segments"]
