"""Gradient-boosted trees for the log loss, on binned features, in numpy."""

from __future__ import annotations

import numpy as np


class BoostedTrees:
    """Complete trees of fixed depth; a node without a useful split sends all rows left."""

    def __init__(self, rounds: int = 60, depth: int = 4, rate: float = 0.2, bins: int = 32, l2: float = 1.0, min_hessian: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.l2, self.min_hessian = rounds, depth, rate, bins, l2, min_hessian
        self.base = 0.0
        self.features = np.zeros((0, 0), np.int32)
        self.cuts = np.zeros((0, 0))
        self.leaves = np.zeros((0, 0))

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        n, width = x.shape
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.bins + 1)[1:-1])) for f in range(width)]
        binned = np.stack([np.searchsorted(edges[f], x[:, f], side="left") for f in range(width)], axis=1)
        share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.base = float(np.log(share / (1 - share)))
        odds = np.full(n, self.base)
        inner = 2**self.depth - 1
        features, cuts = np.zeros((self.rounds, inner), np.int32), np.full((self.rounds, inner), np.inf)
        leaves = np.zeros((self.rounds, inner + 1))
        for t in range(self.rounds):
            p = 1 / (1 + np.exp(-odds))
            g, h = p - y, p * (1 - p)
            node = np.zeros(n, np.int64)
            for level in range(self.depth):
                first, count = 2**level - 1, 2**level
                best = np.full(count, 1e-6)
                for f in range(width):
                    at = node * self.bins + binned[:, f]
                    left_g = np.bincount(at, g, count * self.bins).reshape(count, self.bins).cumsum(1)
                    left_h = np.bincount(at, h, count * self.bins).reshape(count, self.bins).cumsum(1)
                    right_g, right_h = left_g[:, -1:] - left_g, left_h[:, -1:] - left_h
                    gain = left_g**2 / (left_h + self.l2) + right_g**2 / (right_h + self.l2) - left_g[:, -1:] ** 2 / (left_h[:, -1:] + self.l2)
                    gain[(left_h < self.min_hessian) | (right_h < self.min_hessian)] = 0
                    gain = gain[:, : len(edges[f])]
                    if not gain.shape[1]:
                        continue
                    top = gain.argmax(1)
                    value = gain[np.arange(count), top]
                    for i in np.flatnonzero(value > best):
                        best[i] = value[i]
                        features[t, first + i], cuts[t, first + i] = f, edges[f][top[i]]
                node = 2 * node + (x[np.arange(n), features[t, first + node]] > cuts[t, first + node])
            total_g, total_h = np.bincount(node, g, inner + 1), np.bincount(node, h, inner + 1)
            leaves[t] = -self.rate * total_g / (total_h + self.l2)
            odds += leaves[t][node]
        self.features, self.cuts, self.leaves = features, cuts, leaves
        return self

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        rows = np.arange(len(x))
        odds = np.full(len(x), self.base)
        for t in range(len(self.features)):
            node = np.zeros(len(x), np.int64)
            for level in range(self.depth):
                at = 2**level - 1 + node
                node = 2 * node + (x[rows, self.features[t, at]] > self.cuts[t, at])
            odds += self.leaves[t][node]
        return odds
