"""Gradient-boosted trees for two classes: histogram splits, second-order leaves, numpy only."""

from __future__ import annotations

import numpy as np


class BoostedTrees:
    def __init__(self, trees: int = 90, depth: int = 5, rate: float = 0.2, bins: int = 32, l2: float = 1.0, least: float = 5.0):
        self.trees, self.depth, self.rate, self.bins, self.l2, self.least = trees, depth, rate, bins, l2, least
        self.base = 0.0
        self.splits: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None) -> "BoostedTrees":
        w = np.ones(len(y)) if weight is None else weight
        rate = np.clip((w * y).sum() / max(1e-9, w.sum()), 1e-3, 1 - 1e-3)
        self.base = float(np.log(rate / (1 - rate)))
        cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) for j in range(x.shape[1])]
        coded = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], axis=1)
        score = np.full(len(y), self.base)
        for _ in range(self.trees):
            p = 1 / (1 + np.exp(-score))
            score += self._grow(coded, cuts, w * (p - y), w * np.maximum(p * (1 - p), 1e-6))
        return self

    def _grow(self, coded: np.ndarray, cuts: list[np.ndarray], g: np.ndarray, h: np.ndarray) -> np.ndarray:
        n_nodes, d, b = 2 ** (self.depth + 1) - 1, coded.shape[1], self.bins
        feature, cut, value = np.full(n_nodes, -1), np.zeros(n_nodes), np.zeros(n_nodes)
        node = np.zeros(len(g), np.int64)
        for level in range(self.depth + 1):
            first, width = 2**level - 1, 2**level
            local = node - first
            gt, ht = np.bincount(local, g, width), np.bincount(local, h, width)
            value[first : first + width] = -self.rate * gt / (ht + self.l2)
            if level == self.depth:
                break
            best, at, by = np.full(width, 1e-3), np.zeros(width, int), np.full(width, -1)
            for j in range(d):
                if not len(cuts[j]):
                    continue
                slot = local * b + coded[:, j]
                gl = np.bincount(slot, g, width * b).reshape(width, b).cumsum(axis=1)[:, : len(cuts[j])]
                hl = np.bincount(slot, h, width * b).reshape(width, b).cumsum(axis=1)[:, : len(cuts[j])]
                gr, hr = gt[:, None] - gl, ht[:, None] - hl
                gain = gl**2 / (hl + self.l2) + gr**2 / (hr + self.l2) - (gt**2 / (ht + self.l2))[:, None]
                gain[(hl < self.least / 4) | (hr < self.least / 4)] = 0
                i = gain.argmax(axis=1)
                top = gain[np.arange(width), i]
                better = top > best
                best[better], at[better], by[better] = top[better], i[better], j
            for k in np.flatnonzero(by >= 0):
                feature[first + k], cut[first + k] = by[k], cuts[by[k]][at[k]]
            split = feature[node] >= 0
            # Rows of a leaf move to its left child, which repeats the leaf's value.
            right = np.zeros(len(g), bool)
            right[split] = coded[split, feature[node[split]]] > at[local[split]]
            node = 2 * node + 1 + right
        self.splits.append((feature, cut, value))
        return value[node]

    def predict(self, x: np.ndarray) -> np.ndarray:
        """Log-odds of class 1."""
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for feature, cut, value in self.splits:
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                f = feature[node]
                node = 2 * node + 1 + ((f >= 0) & (x[rows, np.maximum(f, 0)] > cut[node]))
            out += value[node]
        return out
