"""A model that runs where the data is: no calls, no limits, whole batches at once.

An ``.onnx`` file is run by onnxruntime (texts in, texts out); an ``.npz`` file is a small retrieval model of this package:
hashed word vectors of known prompts beside their answers, nearest prompt first. Each worker process opens the model once.
"""

from __future__ import annotations

import zlib

import numpy as np

from evalengine.responders.base import Request, Responder, Response

WIDE = 512


def embedded(texts: list[str]) -> np.ndarray:
    """Unit vectors of hashed words."""
    out = np.zeros((len(texts), WIDE))
    for i, t in enumerate(texts):
        for w in t.split():
            out[i, zlib.crc32(w.encode()) % WIDE] += 1
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-12)


def remember(path: str, prompts: list[str], answers: list[str]) -> str:
    """Write a retrieval model; its size is that of the bounded list it is made from."""
    order = sorted(range(len(prompts)), key=lambda i: (prompts[i], answers[i]))
    np.savez(path, vectors=embedded([prompts[i] for i in order]), answers=np.array([answers[i] for i in order], str))
    return path


class LocalResponder(Responder):
    def __init__(self, path: str) -> None:
        self.path = path

    def open(self) -> None:
        if self.path.endswith(".onnx"):
            import onnxruntime

            session = onnxruntime.InferenceSession(self.path)
            name = session.get_inputs()[0].name
            self.run = lambda texts: [str(x) for x in session.run(None, {name: np.array(texts, object)})[0]]
        else:
            held = np.load(self.path)
            vectors, answers = held["vectors"], held["answers"]
            self.run = lambda texts: answers[np.argmax(np.round(embedded(texts) @ vectors.T, 9), axis=1)].tolist() if len(answers) else [None] * len(texts)

    def answer_many(self, requests: list[Request]) -> list[Response]:
        texts = self.run([r.prompt for r in requests])
        return [Response(t, len(r.prompt.split()), len((t or "").split())) for r, t in zip(requests, texts, strict=True)]

    def answer(self, request: Request) -> Response:
        return self.answer_many([request])[0]
