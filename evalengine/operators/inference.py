"""Distinct requests, lanes, and the one stage that calls a model."""

from __future__ import annotations

import time
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evalengine.functions.distributions import uniform
from evalengine.operators.cache import key_expr
from evalengine.operators.throttle import LaneBucket, lane_share
from evalengine.responders.base import Request, Response, RetryPolicy, Retrying, pooled

RESPONSES = "cache_key string, response_text string, prompt_tokens int, completion_tokens int, latency_ms double, attempts int, error string"


@dataclass(frozen=True)
class CallPolicy:
    batch_size: int = 50
    rpm: float | None = None
    tpm: float | None = None
    lanes: int = 8
    slots: int = 1
    initial_fill: float = 1.0
    on_error: str = "row"
    barrier: bool = False
    weights: tuple[float, ...] | None = None
    whole_batches: bool = False
    retry: RetryPolicy = RetryPolicy()


def keyed(df: DataFrame, spec: dict, framing: str = "length") -> DataFrame:
    """Add the request columns and the cache key to rows with ``prompt``."""
    df = df.withColumns({"model_id": F.lit(spec["model"]), "provider_id": F.lit(spec["provider"]), "temperature": F.lit(float(spec.get("temperature", 0.0))), "max_tokens": F.lit(int(spec.get("max_tokens", 1024)))})
    return df.withColumn("cache_key", key_expr(F.col("prompt"), F.col("model_id"), F.col("provider_id"), F.col("temperature"), F.col("max_tokens"), framing))


def distinct_requests(df: DataFrame) -> DataFrame:
    """One row for each key: a hot prompt is called once. Rows that share it carry the least reference of theirs."""
    carried = [c for c in ("prompt", "reference", "model_id", "provider_id", "temperature", "max_tokens") if c in df.columns]
    return df.groupBy("cache_key").agg(*(F.min(c).alias(c) for c in carried))


def lane_of(key: Column, lanes: int) -> Column:
    """The lane of a key: the first 32 bits of its digest, in equal parts, which spreads calls and tokens evenly."""
    return F.floor(uniform(F.lit("lane"), key) * lanes).cast("int")


def assign_lanes(df: DataFrame, lanes: int) -> DataFrame:
    """Deal requests to lanes by key digest; a retried stage deals them alike. Lane k is partition k, so no task holds
    two lanes and none is spare."""
    return df.withColumn("lane", lane_of(F.col("cache_key"), lanes)).repartitionById(lanes, "lane")


def attach(df: DataFrame, responses: DataFrame) -> DataFrame:
    return df.join(responses, "cache_key", "left")


def call_model(requests: DataFrame, spec: dict, policy: CallPolicy = CallPolicy()) -> DataFrame:
    """Call the model for each request. Lanes are tasks; each divides the budget and keeps ``slots`` calls in flight.

    The result must be consumed by one write only: evaluating it again would call again.
    """
    shares = [lane_share(x, policy.lanes, list(policy.weights) if policy.weights else None) for x in (policy.rpm, policy.tpm)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        responder = Retrying(pooled(spec), policy.retry, time.sleep)
        lane = TaskContext.get().partitionId()
        bucket = LaneBucket(shares[0][lane], shares[1][lane], time.monotonic, time.sleep, policy.initial_fill)

        def one(request: Request) -> Response:
            begun = time.monotonic()
            answer = responder.answer(request)
            if answer.error and policy.on_error == "fail":
                raise RuntimeError(answer.error)
            return answer if answer.latency_ms else Response(answer.text, answer.prompt_tokens, answer.completion_tokens, 1000 * (time.monotonic() - begun), answer.attempts, answer.error)

        with ThreadPoolExecutor(policy.slots) as pool:
            for frame in batches:
                rows = frame.to_dict("records")
                for at in range(0, len(rows), policy.batch_size):
                    part = [Request(r["cache_key"], r["prompt"] or "", r.get("reference")) for r in rows[at : at + policy.batch_size]]
                    if policy.whole_batches:
                        for r in part:
                            bucket.acquire(-(-len(r.prompt) // 4))
                        out = responder.answer_many(part)
                    else:
                        futures = []
                        for r in part:
                            bucket.acquire(-(-len(r.prompt) // 4))
                            futures.append(pool.submit(one, r))
                        out = [f.result() for f in futures]
                    yield pd.DataFrame({"cache_key": [r.key for r in part], "response_text": [a.text for a in out], "prompt_tokens": [a.prompt_tokens for a in out], "completion_tokens": [a.completion_tokens for a in out], "latency_ms": [a.latency_ms for a in out], "attempts": [a.attempts for a in out], "error": [a.error for a in out]})

    columns = [c for c in ("cache_key", "prompt", "reference") if c in requests.columns]
    return assign_lanes(requests, policy.lanes).select(*columns).mapInPandas(run, RESPONSES, barrier=policy.barrier)
