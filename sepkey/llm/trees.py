"""Small learners for bounded samples, in numpy: boosted trees over binned dense features, and isotonic regression."""

from __future__ import annotations

import numpy as np


def isotonic(raw: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Knots (raw, probability) of the non-decreasing fit by pooling adjacent violators: mean raw value and rate of each pool."""
    weight = np.ones(len(raw)) if weight is None else weight
    order = np.argsort(raw, kind="stable")
    pools: list[list[float]] = []  # weight, weighted label, weighted raw
    for x, t, w in zip(raw[order].tolist(), y[order].tolist(), weight[order].tolist(), strict=True):
        pools.append([w, w * t, w * x])
        while len(pools) > 1 and pools[-2][1] * pools[-1][0] >= pools[-1][1] * pools[-2][0]:
            last = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], last, strict=True)]
    return np.array([p[2] / p[0] for p in pools]), np.array([p[1] / p[0] for p in pools])


class BoostedTrees:
    """Gradient boosting on the logistic loss: trees of fixed depth over at most ``bins`` quantile bins a feature."""

    def __init__(self, rounds: int = 80, depth: int = 3, rate: float = 0.15, bins: int = 32, ridge: float = 1.0, least: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.ridge, self.least = rounds, depth, rate, bins, ridge, least
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.base = 0.0

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        n, width = x.shape
        grid = np.linspace(0, 1, self.bins + 1)[1:-1]
        self.edges = [np.unique(np.quantile(x[:, f], grid)) for f in range(width)]
        binned = self._binned(x)
        rate = min(max(y.mean(), 1e-6), 1 - 1e-6)
        self.base = float(np.log(rate / (1 - rate)))
        score = np.full(n, self.base)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            tree = self._tree(binned, p - y, np.maximum(p * (1 - p), 1e-9))
            self.trees.append(tree)
            score += self._apply(tree, binned)
        return self

    def _binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, f], "right") for f, e in enumerate(self.edges)], axis=1).astype(np.int64)

    def _tree(self, binned, g, h):
        nodes = 1 << self.depth
        feature, cut = np.zeros(nodes, np.int64), np.full(nodes, 1 << 30)
        at = np.ones(len(g), np.int64)  # heap order: node i has children 2i and 2i + 1
        for level in range(self.depth):
            count = 1 << level
            here = at - count
            best = np.full(count, 1e-9)
            for f in range(binned.shape[1]):
                size = len(self.edges[f]) + 1
                if size < 2:
                    continue
                key = here * size + binned[:, f]
                gs = np.bincount(key, g, count * size).reshape(count, size)
                hs = np.bincount(key, h, count * size).reshape(count, size)
                gl, hl = np.cumsum(gs, axis=1)[:, :-1], np.cumsum(hs, axis=1)[:, :-1]
                gt, ht = gs.sum(axis=1, keepdims=True), hs.sum(axis=1, keepdims=True)
                gr, hr = gt - gl, ht - hl
                gain = gl**2 / (hl + self.ridge) + gr**2 / (hr + self.ridge) - gt**2 / (ht + self.ridge)
                gain[(hl < self.least) | (hr < self.least)] = 0
                top = gain.argmax(axis=1)
                better = gain[np.arange(count), top] > best
                best[better] = gain[np.arange(count), top][better]
                feature[count : 2 * count][better] = f
                cut[count : 2 * count][better] = top[better]
            at = 2 * at + (binned[np.arange(len(g)), feature[at]] > cut[at])
        leaf = at - nodes
        gs, hs = np.bincount(leaf, g, nodes), np.bincount(leaf, h, nodes)
        return feature, cut, -self.rate * gs / (hs + self.ridge)

    def _apply(self, tree, binned):
        feature, cut, value = tree
        at = np.ones(len(binned), np.int64)
        rows = np.arange(len(binned))
        for _ in range(self.depth):
            at = 2 * at + (binned[rows, feature[at]] > cut[at])
        return value[at - len(value)]

    def raw(self, x: np.ndarray) -> np.ndarray:
        binned = self._binned(x)
        return self.base + sum((self._apply(t, binned) for t in self.trees), np.zeros(len(x)))
