"""Gradient-boosted regression trees for binary labels, in numpy: small, deterministic, calibrated."""

from __future__ import annotations

import numpy as np


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class BoostedTrees:
    """Trees of fixed depth on quantile-binned features, fitted to the gradient of the logistic loss."""

    def __init__(self, rounds: int = 40, depth: int = 3, rate: float = 0.3, bins: int = 16, ridge: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.ridge = rounds, depth, rate, bins, ridge

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        self.cuts = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        b = self._bin(x)
        mean = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.bias = float(np.log(mean / (1 - mean)))
        f, self.trees = np.full(len(y), self.bias), []
        for _ in range(self.rounds):
            p = sigmoid(f)
            g, h = y - p, p * (1 - p)
            node, tree = np.zeros(len(y), np.int64), []
            for level in range(self.depth):
                n = 1 << level
                best = np.zeros(n), np.zeros(n, np.int64), np.full(n, self.bins, np.int64)
                for j in range(x.shape[1]):
                    at = node * self.bins + b[:, j]
                    gs, hs = (np.cumsum(np.bincount(at, v, n * self.bins).reshape(n, self.bins), 1) for v in (g, h))
                    gain = gs**2 / (hs + self.ridge) + (gs[:, -1:] - gs) ** 2 / (hs[:, -1:] - hs + self.ridge) - gs[:, -1:] ** 2 / (hs[:, -1:] + self.ridge)
                    k = gain.argmax(1)
                    top = gain[np.arange(n), k]
                    more = top > best[0] + 1e-9
                    best[0][more], best[1][more], best[2][more] = top[more], j, k[more]
                tree.append((best[1], best[2]))
                node = node * 2 + (b[np.arange(len(y)), best[1][node]] > best[2][node])
            leaves = 1 << self.depth
            value = self.rate * np.bincount(node, g, leaves) / (np.bincount(node, h, leaves) + self.ridge)
            self.trees.append((tree, value))
            f += value[node]
        return self

    def _bin(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, v, side="left") for c, v in zip(self.cuts, x.T, strict=True)], 1)

    def raw(self, x: np.ndarray) -> np.ndarray:
        b, f = self._bin(x), np.full(len(x), self.bias)
        for tree, value in self.trees:
            node = np.zeros(len(x), np.int64)
            for feature, cut in tree:
                node = node * 2 + (b[np.arange(len(x)), feature[node]] > cut[node])
            f += value[node]
        return f


def calibrate(f: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and intercept that make sigmoid(a f + b) a probability, by Newton's steps with smoothed labels."""
    pos, neg = y.sum(), (1 - y).sum()
    t = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = sigmoid(a * f + b)
        w = np.maximum(p * (1 - p), 1e-9)
        grad = np.array([((p - t) * f).sum(), (p - t).sum()])
        hess = np.array([[(w * f * f).sum() + 1e-6, (w * f).sum()], [(w * f).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(hess, grad)
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(a), float(b)
