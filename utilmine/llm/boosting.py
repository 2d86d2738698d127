"""Gradient boosted trees for binary targets, small enough to broadcast: histogram splits, logistic loss, numpy only."""

from __future__ import annotations

import numpy as np


class Boosted:
    """Trees of a fixed depth as complete binary arrays: feature and threshold of inner nodes, values of leaves."""

    def __init__(self, depth: int = 3, trees: int = 40, rate: float = 0.3, least: int = 20, ridge: float = 1.0):
        self.depth, self.n, self.rate, self.least, self.ridge = depth, trees, rate, least, ridge
        self.base, self.trees, self.scale = 0.0, [], (1.0, 0.0)

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        p = y.mean()
        self.base = float(np.log(p / (1 - p)))
        score = np.full(len(y), self.base)
        cuts = [np.unique(np.quantile(c, np.linspace(0, 1, 33)[1:-1])) for c in x.T]
        bins = np.stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T, strict=True)], 1)
        for _ in range(self.n):
            q = 1 / (1 + np.exp(-score))
            tree = self._grow(bins, cuts, y - q, q * (1 - q))
            self.trees.append(tree)
            score += self._leaves(x, tree)
        return self

    def _grow(self, bins, cuts, gradient, curvature):
        inner = (1 << self.depth) - 1
        feature, threshold, value = np.zeros(inner, int), np.full(inner, np.inf), np.zeros(1 << self.depth)
        node = np.zeros(len(bins), int)
        for at in range(inner):
            rows = np.flatnonzero(node == at)
            g, h = gradient[rows], curvature[rows]
            best = 1e-6
            for f, c in enumerate(cuts):
                if len(rows) < 2 * self.least or not len(c):
                    continue
                gs, hs, ns = (np.cumsum(np.bincount(bins[rows, f], w, len(c) + 1))[:-1] for w in (g, h, None))
                G, H = g.sum(), h.sum()
                gain = gs**2 / (hs + self.ridge) + (G - gs) ** 2 / (H - hs + self.ridge) - G**2 / (H + self.ridge)
                gain[(ns < self.least) | (len(rows) - ns < self.least)] = -1
                k = int(gain.argmax())
                if gain[k] > best:
                    best, feature[at], threshold[at] = gain[k], f, c[k]
            right = bins[rows, feature[at]] > (np.searchsorted(cuts[feature[at]], threshold[at], "left") if np.isfinite(threshold[at]) else np.inf)
            node[rows] = 2 * at + 1 + right
        leaf = node - inner
        for k in range(1 << self.depth):
            rows = leaf == k
            value[k] = self.rate * gradient[rows].sum() / (curvature[rows].sum() + self.ridge)
        return feature, threshold, value

    def _leaves(self, x, tree):
        feature, threshold, value = tree
        node = np.zeros(len(x), int)
        for _ in range(self.depth):
            node = 2 * node + 1 + (x[np.arange(len(x)), feature[node]] > threshold[node])
        return value[node - len(feature)]

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.base + sum(self._leaves(x, t) for t in self.trees)

    def calibrate(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        """Platt scaling on held-out rows: two parameters by Newton steps."""
        s, a, b = self.raw(x), 1.0, 0.0
        goal = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
        for _ in range(20):
            p = 1 / (1 + np.exp(-(a * s + b)))
            w = p * (1 - p) + 1e-9
            H = np.array([[(w * s * s).sum() + 1e-3, (w * s).sum()], [(w * s).sum(), w.sum() + 1e-3]])
            step = np.linalg.solve(H, np.array([((goal - p) * s).sum(), (goal - p).sum()]))
            a, b = a + step[0], b + step[1]
        self.scale = (float(a), float(b))
        return self

    def probability(self, x: np.ndarray) -> np.ndarray:
        a, b = self.scale
        return 1 / (1 + np.exp(-np.clip(a * self.raw(x) + b, -40, 40)))


def threshold_for(probability: np.ndarray, y: np.ndarray, precision: float) -> float:
    """The least threshold at which the accepted rows have this precision; above one if there is none."""
    order = np.argsort(-probability)
    right = np.cumsum(y[order]) / np.arange(1, len(y) + 1)
    last = np.append(probability[order][:-1] != probability[order][1:], True)
    good = np.flatnonzero((right >= precision) & last)
    return float(probability[order][good[-1]]) if len(good) else 2.0
