"""The specification tree of an evaluation: typed, validated, and the same after a round trip through JSON."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, field, fields
from typing import Any

from evalengine.operators.cache import POLICIES
from evalengine.operators.intervals import ENGINES


class SpecError(ValueError):
    pass


def _need(ok: bool, what: str) -> None:
    if not ok:
        raise SpecError(what)


@dataclass(frozen=True)
class ResponderSpec:
    provider: str = "simulated"
    model: str = "model-a"
    temperature: float = 0.0
    max_tokens: int = 1024
    params: dict[str, Any] = field(default_factory=dict)

    def __post_init__(self) -> None:
        _need(self.temperature >= 0, "temperature is negative")
        _need(self.max_tokens > 0, "max_tokens must be positive")


@dataclass(frozen=True)
class CallSpec:
    batch_size: int = 50
    rpm: float | None = None
    tpm: float | None = None
    lanes: int = 8
    slots: int = 1
    initial_fill: float = 1.0
    cache_policy: str = "read_write"
    cache_path: str | None = None
    ttl_days: int | None = None

    def __post_init__(self) -> None:
        _need(self.cache_policy in POLICIES, f"unknown cache policy {self.cache_policy}")
        _need(self.rpm is None or self.rpm > 0, "rpm must be positive or null")
        _need(self.tpm is None or self.tpm > 0, "tpm must be positive or null")
        _need(min(self.batch_size, self.lanes, self.slots) > 0, "batch_size, lanes and slots must be positive")


@dataclass(frozen=True)
class MetricSpec:
    name: str
    family: str = "lexical"
    kind: str = "continuous"
    options: dict[str, Any] = field(default_factory=dict)

    def __post_init__(self) -> None:
        _need(self.family in ("lexical", "semantic", "judge", "rag", "custom"), f"unknown family {self.family}")
        _need(self.kind in ("binary", "ordinal", "continuous", "complex"), f"unknown kind {self.kind}")


@dataclass(frozen=True)
class StatisticsSpec:
    level: float = 0.95
    iterations: int = 1000
    interval: str = "auto"
    engine: str = "auto"
    alpha: float = 0.05
    segments: tuple[str, ...] = ()

    def __post_init__(self) -> None:
        _need(0 < self.level < 1, "level must lie between 0 and 1")
        _need(self.iterations >= 100, "at least 100 iterations")
        _need(self.interval in ("auto", "percentile", "bca", "t", "wilson", "wald"), f"unknown interval {self.interval}")
        _need(self.engine in ("auto", *ENGINES), f"unknown engine {self.engine}")


@dataclass(frozen=True)
class DataSpec:
    id_col: str = "example_id"
    template: str = "{{ instruction }}"
    reference_col: str = "reference"


@dataclass(frozen=True)
class EvaluationSpec:
    run_name: str
    metrics: tuple[MetricSpec, ...]
    responder: ResponderSpec = ResponderSpec()
    calls: CallSpec = CallSpec()
    statistics: StatisticsSpec = StatisticsSpec()
    data: DataSpec = DataSpec()
    seed: int = 42
    labels: dict[str, str] = field(default_factory=dict)

    def __post_init__(self) -> None:
        _need(bool(self.run_name), "run_name is empty")
        _need(bool(self.metrics), "no metrics")
        for m in self.metrics:
            _need(self.statistics.interval not in ("wilson", "wald") or m.kind == "binary", f"{self.statistics.interval} needs a binary metric")

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    def fingerprint(self) -> str:
        """Digest of everything but the labels."""
        return hashlib.sha256(json.dumps({k: v for k, v in asdict(self).items() if k != "labels"}, sort_keys=True).encode()).hexdigest()

    @classmethod
    def from_json(cls, text: str) -> EvaluationSpec:
        return _built(cls, json.loads(text))


_PARTS = {"responder": ResponderSpec, "calls": CallSpec, "statistics": StatisticsSpec, "data": DataSpec}


def _built(cls: type, raw: dict):
    unknown = set(raw) - {f.name for f in fields(cls)}
    _need(not unknown, f"unknown fields {sorted(unknown)}")
    out = dict(raw)
    for name, part in _PARTS.items():
        if name in out and cls is EvaluationSpec:
            out[name] = _built(part, out[name])
    if "metrics" in out:
        out["metrics"] = tuple(_built(MetricSpec, m) for m in out["metrics"])
    if "segments" in out:
        out["segments"] = tuple(out["segments"])
    return cls(**out)
