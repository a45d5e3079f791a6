"""Gradient-boosted trees on the driver, for a bounded table of features, and isotonic calibration."""

from __future__ import annotations

import numpy as np

BINS = 48


class Trees:
    """Logistic loss, Newton leaves, full binary trees of one depth over quantile bins."""

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.2, ridge: float = 4.0):
        self.rounds, self.depth, self.rate, self.ridge = rounds, depth, rate, ridge

    def fit(self, x: np.ndarray, y: np.ndarray) -> Trees:
        self.edges = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1])) for c in x.T]
        cells = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(self.edges, x.T, strict=True)], 1)
        n, width = cells.shape
        share = min(max(float(y.mean()), 1e-4), 1 - 1e-4)
        self.start = float(np.log(share / (1 - share)))
        margin, self.trees = np.full(n, self.start), []
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-margin))
            g, h = p - y, p * (1 - p)
            node, splits = np.zeros(n, np.int64), []
            for level in range(self.depth):
                k = 1 << level
                best = np.full(k, 1e-9), np.zeros(k, np.int64), np.full(k, BINS, np.int64)
                for f in range(width):
                    at = node * BINS + cells[:, f]
                    gs, hs = (np.bincount(at, v, k * BINS).reshape(k, BINS) for v in (g, h))
                    gl, hl = gs.cumsum(1), hs.cumsum(1)
                    gt, ht = gl[:, -1:], hl[:, -1:]
                    gain = gl**2 / (hl + self.ridge) + (gt - gl) ** 2 / (ht - hl + self.ridge) - gt**2 / (ht + self.ridge)
                    gain[(hl < 1) | (ht - hl < 1)] = 0
                    cut = gain.argmax(1)
                    better = (top := gain[np.arange(k), cut]) > best[0]
                    best[0][better], best[1][better], best[2][better] = top[better], f, cut[better]
                splits.append((best[1], best[2]))
                node = node * 2 + (cells[np.arange(n), best[1][node]] > best[2][node])
            leaf = -np.bincount(node, g, 1 << self.depth) / (np.bincount(node, h, 1 << self.depth) + self.ridge) * self.rate
            margin += leaf[node]
            self.trees.append((splits, leaf))
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        cells = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(self.edges, x.T, strict=True)], 1)
        out, rows = np.full(len(x), self.start), np.arange(len(x))
        for splits, leaf in self.trees:
            node = np.zeros(len(x), np.int64)
            for feature, cut in splits:
                node = node * 2 + (cells[rows, feature[node]] > cut[node])
            out += leaf[node]
        return out


class Isotonic:
    """Pool-adjacent-violators over (margin, label), drawn as a line between the pools' means; a small part of the
    plain probability keeps the order inside a pool."""

    def fit(self, margin: np.ndarray, y: np.ndarray) -> Isotonic:
        order = np.argsort(margin, kind="stable")
        pools: list[list[float]] = []
        for m, label in zip(margin[order], y[order], strict=True):
            pools.append([float(m), float(label), 1.0])
            while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
                m2, s2, n2 = pools.pop()
                m1, s1, n1 = pools[-1]
                pools[-1] = [(m1 * n1 + m2 * n2) / (n1 + n2), s1 + s2, n1 + n2]
        self.x, self.y = np.array([p[0] for p in pools] or [0.0]), np.array([p[1] / p[2] for p in pools] or [0.0])
        return self

    def probability(self, margin: np.ndarray) -> np.ndarray:
        return np.clip(0.98 * np.interp(margin, self.x, self.y) + 0.02 / (1 + np.exp(-margin)), 0.0, 1.0)
