"""Static split of a global request and token budget over lanes, each with two local token buckets."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def lane_share(limit: float | None, lanes: int, weights: list[float] | None = None) -> list[float | None]:
    """Each lane's part of a per-minute limit; a null limit is none."""
    if limit is None:
        return [None] * lanes
    w = weights or [1.0] * lanes
    return [limit * x / sum(w) for x in w]


class LaneBucket:
    """Balances of requests and tokens that refill continuously up to one minute's share.

    ``acquire`` waits until both balances cover the call and then debits them. A call larger than the bucket waits
    for its whole cost and leaves a negative balance. ``initial_fill`` 1 starts full, 0 empty (as after a retry).
    """

    def __init__(self, rpm: float | None, tpm: float | None, clock: Callable[[], float], sleep: Callable[[float], None], initial_fill: float = 1.0) -> None:
        self.caps = (rpm, tpm)
        self.held = [initial_fill * c if c is not None else 0.0 for c in self.caps]
        self.clock, self.sleep, self.seen = clock, sleep, clock()

    def acquire(self, tokens: float) -> float:
        now, wait = self.clock(), 0.0
        for k, (cap, cost) in enumerate(zip(self.caps, (1.0, tokens), strict=True)):
            if cap is not None:
                self.held[k] = min(cap, self.held[k] + (now - self.seen) * cap / 60)
                if self.held[k] < cost:
                    wait = max(wait, (cost - self.held[k]) * 60 / cap)
        self.seen = now
        if wait:
            self.sleep(wait)
            later = self.clock()
            for k, cap in enumerate(self.caps):
                if cap is not None:
                    self.held[k] += (later - self.seen) * cap / 60
            self.seen = later
        for k, (cap, cost) in enumerate(zip(self.caps, (1.0, tokens), strict=True)):
            if cap is not None:
                self.held[k] -= cost
        return wait


class LaneClock:
    """A lane in virtual time: its bucket, and the ends of the calls in flight. It takes calls in order, a batch at a time."""

    def __init__(self, begin: float, rpm: float | None, tpm: float | None, slots: int, initial_fill: float = 1.0) -> None:
        self.now, self.slots, self.busy = begin, slots, []
        self.bucket = LaneBucket(rpm, tpm, lambda: self.now, self._wait, initial_fill)

    def _wait(self, seconds: float) -> None:
        self.now += seconds

    def take(self, arrival: np.ndarray, tokens: np.ndarray, latency: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        start, end = np.zeros(len(arrival)), np.zeros(len(arrival))
        for i in range(len(arrival)):
            self.now = max(self.now, float(arrival[i]))
            if len(self.busy) == self.slots:
                self.now = max(self.now, heapq.heappop(self.busy))
            self.bucket.acquire(float(tokens[i]))
            start[i], end[i] = self.now, self.now + latency[i]
            heapq.heappush(self.busy, end[i])
        return start, end


def admissions(arrival: np.ndarray, tokens: np.ndarray, latency: np.ndarray, rpm: float | None, tpm: float | None, slots: int, initial_fill: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
    """Virtual-time start and end of a lane's calls, in order, with at most ``slots`` in flight."""
    return LaneClock(float(arrival[0]) if len(arrival) else 0.0, rpm, tpm, slots, initial_fill).take(arrival, tokens, latency)


def simulate_fold(calls: DataFrame, rpm: float | None, tpm: float | None, lanes: int, slots: int, lane: str = "lane", order: str = "call_id") -> DataFrame:
    """Both budgets and a concurrency limit, one fold a lane. ``calls``: lane, order, arrival_s, tokens, latency_s.

    A lane's calls arrive sorted, batch after batch; what is held between batches is one bucket and the calls in flight.
    """
    shares = (None if rpm is None else rpm / lanes, None if tpm is None else tpm / lanes)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, clock = None, None
        for b in batches:
            for name, calls_of in b.groupby(lane, sort=False):
                x = [calls_of[c].to_numpy(np.float64) for c in ("arrival_s", "tokens", "latency_s")]
                if clock is None or name != at:
                    at, clock = name, LaneClock(float(x[0][0]), *shares, slots)
                start, end = clock.take(*x)
                yield calls_of[[lane, order]].assign(start_s=start, end_s=end)

    kind = dict(calls.dtypes)
    sorted_calls = calls.select(lane, order, "arrival_s", "tokens", "latency_s").repartition(lanes, lane).sortWithinPartitions(lane, order)
    return sorted_calls.mapInPandas(run, f"{lane} {kind[lane]}, {order} {kind[order]}, start_s double, end_s double")


def simulate_windows(calls: DataFrame, cost: Column, cap: float, lane: str = "lane", order: str = "call_id", arrival: str = "arrival_s") -> DataFrame:
    """One budget in closed form: two running scans a lane, all in the plan.

    With C the running cost and r the refill rate, the time by which the bucket has earned call k's cost is
    C_k/r plus the largest idle offset so far; a full bucket is worth a minute.
    """
    rate = cap / 60
    w = Window.partitionBy(lane).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    spent = calls.withColumn("_cost", cost.cast("double")).withColumn("_spent", F.sum("_cost").over(w))
    earned = spent.withColumn("_earned", F.col("_spent") / rate + F.max(F.col(arrival) - (F.col("_spent") - F.col("_cost")) / rate).over(w))
    return earned.withColumn("admitted_s", F.max(F.greatest(F.col(arrival), F.col("_earned") - 60)).over(w)).drop("_cost", "_spent", "_earned")


def violations(calls: DataFrame, limit: int, time: str = "arrival", unit: str = "minute") -> DataFrame:
    """Units of time in which uncoordinated calls exceed the limit."""
    return calls.groupBy(F.date_trunc(unit, F.col(time)).alias(unit)).agg(F.count("*").alias("calls")).where(F.col("calls") > limit)
