"""A stand-in for a remote model: a deterministic edit of the reference, chosen by digest.

The same rule exists as a Column (``respond``) and as a batch responder (``SimulatedResponder``).
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column
from pyspark.sql import functions as F

from evalengine.functions.distributions import uniform
from evalengine.responders.base import Request, Responder, Response

UNRELATED = "no answer is known"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def respond(model: str, quality: float, key: Column, reference: Column) -> Column:
    u, words = uniform(F.lit(model), key), F.split(reference, " ")
    return (
        F.when(u < 0.6 * quality, reference)
        .when(u < quality, F.concat(F.translate(reference, LOWER, LOWER.upper()), F.lit("!")))
        .when(u < quality + 0.5 * (1 - quality), F.array_join(F.filter(words, lambda w, i: i % 3 != 2), " "))
        .when(u < quality + 0.8 * (1 - quality), F.array_join(F.reverse(words), " "))
        .otherwise(UNRELATED)
    )


def latency_ms(model: str, key: Column) -> Column:
    """Skewed: most calls near 300 ms, one in a hundred near 1,000 ms."""
    u = uniform(F.lit(f"latency {model}"), key)
    return 250 + 110 * -F.log(1 - u * 0.999)


class SimulatedResponder(Responder):
    def __init__(self, model: str, quality: float) -> None:
        self.model, self.quality = model, quality

    def answer(self, request: Request) -> Response:
        u = int(hashlib.sha256(f"{self.model}:{request.key}".encode()).hexdigest()[:8], 16) / 4294967296
        text, q = request.reference or "", self.quality
        words = text.split(" ")
        if u >= 0.6 * q:
            if u < q:
                text = text.translate(str.maketrans(LOWER, LOWER.upper())) + "!"
            elif u < q + 0.5 * (1 - q):
                text = " ".join(w for i, w in enumerate(words) if i % 3 != 2)
            else:
                text = " ".join(reversed(words)) if u < q + 0.8 * (1 - q) else UNRELATED
        return Response(text, -(-len(request.prompt) // 4), -(-len(text) // 4))


class SimulatedJudge(Responder):
    """A stand-in grader. It reads the answer out of the prompt, compares it with the request's reference by token F1, and
    gives a score in one of four shapes; one verdict in a hundred holds none. ``judge.simulated_verdict`` is its Column."""

    def answer(self, request: Request) -> Response:
        said = request.prompt.rpartition("\nAnswer: ")[2].removesuffix("\nGive a score and an explanation.")
        words = lambda t: re.sub(r"[!-/:-@\[-`{-~]", "", t.lower()).split()
        a, b = words(said), words(request.reference or "")
        both = sum(min(a.count(w), b.count(w)) for w in set(a))
        quality = 1.0 if not a and not b else 2.0 * both / (len(a) + len(b))
        u, v = (int(hashlib.sha256(f"{k}:{request.key}".encode()).hexdigest()[:8], 16) / 4294967296 for k in ("judge", "shape"))
        score = str(max(1, min(5, int(1 + 4 * quality + (u - 0.5) + 0.5))))
        shaped = f"Score: {score}" if v < 0.25 else f"{score}/5 in all" if v < 0.5 else f"[[{score}]]" if v < 0.75 else f'{{"score": {score}}}'
        text = "a helpful answer" if u < 0.01 else shaped
        return Response(text, -(-len(request.prompt) // 4), -(-len(text) // 4))


class SimulatedVerifier(Responder):
    """A stand-in that says whether a context in the prompt holds a claim word for word."""

    def answer(self, request: Request) -> Response:
        claim, _, context = request.prompt.partition("\nContext: ")
        text = "supported" if claim.removeprefix("Claim: ") in context else "not supported"
        return Response(text, -(-len(request.prompt) // 4), -(-len(text) // 4))
