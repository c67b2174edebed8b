"""Gradient-boosted trees over histograms, and isotonic calibration, in numpy."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class Boosted:
    """Logistic boosting of trees of a fixed depth; features are cut at quantiles of the sample."""

    trees: int = 60
    depth: int = 3
    rate: float = 0.2
    bins: int = 48
    least: float = 5.0
    penalty: float = 1.0
    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    splits: np.ndarray | None = None  # feature and bin of each inner node of each tree
    leaves: np.ndarray | None = None

    def binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(self.edges)], axis=1)

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> "Boosted":
        n, width = x.shape
        self.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins)[:-1])) for j in range(width)]
        cells, inner = self.binned(x), (1 << self.depth) - 1
        bins = self.bins + 1
        mean = min(max(np.average(y, weights=weight), 1e-6), 1 - 1e-6)
        self.base = float(np.log(mean / (1 - mean)))
        self.splits, self.leaves = np.zeros((self.trees, inner, 2), dtype=np.int32), np.zeros((self.trees, 1 << self.depth))
        margin = np.full(n, self.base)
        for t in range(self.trees):
            p = 1 / (1 + np.exp(-margin))
            g, h = weight * (y - p), weight * np.maximum(p * (1 - p), 1e-9)
            node = np.zeros(n, dtype=np.int64)
            for level in range(self.depth):
                count = 1 << level
                gain, cut = np.full((count, width), -np.inf), np.zeros((count, width), dtype=np.int32)
                for j in range(width):
                    key = node * bins + cells[:, j]
                    left_g = np.bincount(key, g, count * bins).reshape(count, bins).cumsum(axis=1)
                    left_h = np.bincount(key, h, count * bins).reshape(count, bins).cumsum(axis=1)
                    all_g, all_h = left_g[:, -1:], left_h[:, -1:]
                    worth = left_g**2 / (left_h + self.penalty) + (all_g - left_g) ** 2 / (all_h - left_h + self.penalty) - all_g**2 / (all_h + self.penalty)
                    worth[(left_h < self.least / 20) | (all_h - left_h < self.least / 20)] = -np.inf
                    cut[:, j] = worth.argmax(axis=1)
                    gain[:, j] = worth.max(axis=1)
                best = gain.argmax(axis=1)
                rows = np.arange(count)
                place = np.where(np.isfinite(gain[rows, best]) & (gain[rows, best] > 1e-9), cut[rows, best], bins)
                self.splits[t, count - 1 : 2 * count - 1] = np.stack([best, place], axis=1)
                node = 2 * node + (cells[np.arange(n), best[node]] > place[node])
            size = 1 << self.depth
            self.leaves[t] = self.rate * np.bincount(node, g, size) / (np.bincount(node, h, size) + self.penalty)
            margin += self.leaves[t][node]
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        cells, rows = self.binned(x), np.arange(len(x))
        out = np.full(len(x), self.base)
        for splits, leaves in zip(self.splits, self.leaves):
            node = np.zeros(len(x), dtype=np.int64)
            for level in range(self.depth):
                feature, place = splits[node + (1 << level) - 1].T
                node = 2 * node + (cells[rows, feature] > place)
            out += leaves[node]
        return out


@dataclass
class Isotonic:
    """The nondecreasing least-squares fit by pooling adjacent violators, linear between its points."""

    x: np.ndarray | None = None
    y: np.ndarray | None = None

    def fit(self, score: np.ndarray, label: np.ndarray, weight: np.ndarray) -> "Isotonic":
        at, which = np.unique(score, return_inverse=True)
        total = np.bincount(which, weight)
        value = np.bincount(which, weight * label) / total
        pools: list[list[float]] = []
        for i in range(len(at)):
            pools.append([value[i], total[i], at[i], at[i]])
            while len(pools) > 1 and pools[-2][0] >= pools[-1][0]:
                v, w, _, last = pools.pop()
                own = pools[-1]
                own[0], own[1], own[3] = (own[0] * own[1] + v * w) / (own[1] + w), own[1] + w, last
        self.x = np.array([p for v, _, a, b in pools for p in (a, b)])
        self.y = np.array([v for v, _, _, _ in pools for _ in (0, 1)])
        return self

    def __call__(self, score: np.ndarray) -> np.ndarray:
        return np.interp(score, self.x, self.y)
