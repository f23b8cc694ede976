"""A random forest for small labelled sets, applied to whole arrays at once."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Tree:
    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    share: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        while True:
            inner = self.feature[at] >= 0
            if not inner.any():
                return self.share[at]
            f = np.maximum(self.feature[at], 0)
            down = np.where(x[np.arange(len(x)), f] <= self.cut[at], self.left[at], self.right[at])
            at = np.where(inner, down, at)


@dataclass
class Forest:
    trees: list[Tree]

    def predict(self, x: np.ndarray) -> np.ndarray:
        """The mean share of the positive class over the trees."""
        return np.mean([t.predict(x) for t in self.trees], axis=0) if len(x) else np.zeros(0)


def _grow(x: np.ndarray, y: np.ndarray, rng: np.random.Generator, tried: int, depth: int, least: int) -> Tree:
    nodes: list[list[float]] = []

    def split(rows: np.ndarray, level: int) -> int:
        me, positive = len(nodes), y[rows].mean()
        nodes.append([-1, 0.0, -1, -1, positive])
        if level == depth or len(rows) < 2 * least or positive in (0.0, 1.0):
            return me
        best = (1e-9, -1, 0.0)
        for f in rng.choice(x.shape[1], tried, replace=False):
            order = np.argsort(x[rows, f], kind="stable")
            v, t = x[rows, f][order], np.cumsum(y[rows][order])
            n = np.arange(1, len(v))
            p, q = t[:-1] / n, (t[-1] - t[:-1]) / (len(v) - n)
            gain = positive * (1 - positive) - (n * p * (1 - p) + (len(v) - n) * q * (1 - q)) / len(v)
            gain[(v[1:] == v[:-1]) | (n < least) | (len(v) - n < least)] = -1
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (float(gain[k]), int(f), float((v[k] + v[k + 1]) / 2))
        if best[1] >= 0:
            go = x[rows, best[1]] <= best[2]
            a, b = split(rows[go], level + 1), split(rows[~go], level + 1)
            nodes[me][:4] = best[1], best[2], a, b
        return me

    split(rng.integers(0, len(x), len(x)), 0)
    feature, cut, left, right, share = (np.array(c) for c in zip(*nodes, strict=True))
    return Tree(feature.astype(np.int64), cut.astype(float), left.astype(np.int64), right.astype(np.int64), share.astype(float))


def grow_forest(x: np.ndarray, y: np.ndarray, trees: int = 30, depth: int = 10, least: int = 2, seed: int = 5) -> Forest:
    rng = np.random.default_rng(seed)
    tried = max(1, round(np.sqrt(x.shape[1])))
    return Forest([_grow(x, y.astype(float), rng, tried, depth, least) for _ in range(trees)])
