"""Gradient-boosted trees for two classes on dense features, and isotonic calibration; plain numpy.

Features are cut into at most 64 bins at quantiles; trees grow level by level from histograms of gradients.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

BINS = 64


@dataclass
class Boosted:
    trees: int = 80
    depth: int = 4
    rate: float = 0.15
    least: float = 8.0
    ridge: float = 1.0
    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    #: Per tree: feature and bin of each inner node in heap order (feature -1: stop, go left), values of the leaves.
    grown: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    def _bin(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(self.edges)], 1).astype(np.int16)

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        self.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS)[1:-1])) for j in range(x.shape[1])] if len(y) else [np.zeros(0)] * x.shape[1]
        b, n = self._bin(x), len(y)
        rate = min(max(y.mean() if n else 0.0, 1e-4), 1 - 1e-4)
        self.base = float(np.log(rate / (1 - rate)))
        f = np.full(n, self.base)
        for _ in range(self.trees if n else 0):
            p = 1 / (1 + np.exp(-f))
            step = self._tree(b, y - p, p * (1 - p))
            f += step
        return self

    def _tree(self, b: np.ndarray, g: np.ndarray, h: np.ndarray) -> np.ndarray:
        inner = (1 << self.depth) - 1
        feature, cut = np.full(inner, -1, np.int16), np.zeros(inner, np.int16)
        node = np.zeros(len(g), np.int64)
        for level in range(self.depth):
            first, width = (1 << level) - 1, 1 << level
            local = node - first
            best = np.full(width, 1e-6)
            for j in range(b.shape[1]):
                key = local * BINS + b[:, j]
                gs = np.cumsum(np.bincount(key, g, width * BINS).reshape(width, BINS), 1)
                hs = np.cumsum(np.bincount(key, h, width * BINS).reshape(width, BINS), 1)
                ga, ha = gs[:, -1:], hs[:, -1:]
                gain = gs**2 / (hs + self.ridge) + (ga - gs) ** 2 / (ha - hs + self.ridge) - ga**2 / (ha + self.ridge)
                gain[(hs < self.least / 8) | (ha - hs < self.least / 8)] = 0
                at = gain.argmax(1)
                top = gain[np.arange(width), at]
                better = top > best
                best[better] = top[better]
                feature[first : first + width][better] = j
                cut[first : first + width][better] = at[better]
            node = 2 * node + 1 + self._right(b, node, feature, cut)
        leaf = node - inner
        values = self.rate * np.bincount(leaf, g, inner + 1) / (np.bincount(leaf, h, inner + 1) + self.ridge)
        self.grown.append((feature, cut, values))
        return values[leaf]

    @staticmethod
    def _right(b: np.ndarray, node: np.ndarray, feature: np.ndarray, cut: np.ndarray) -> np.ndarray:
        f = feature[node]
        return (f >= 0) & (b[np.arange(len(node)), np.maximum(f, 0)] > cut[node])

    def raw(self, x: np.ndarray) -> np.ndarray:
        b, f = self._bin(x), np.full(len(x), self.base)
        for feature, cut, values in self.grown:
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + self._right(b, node, feature, cut)
            f += values[node - len(feature)]
        return f


@dataclass
class Isotonic:
    """A non-decreasing map from raw scores to shares of label 1, by pooling adjacent violators."""

    at: np.ndarray = field(default_factory=lambda: np.zeros(1))
    share: np.ndarray = field(default_factory=lambda: np.zeros(1))

    def fit(self, raw: np.ndarray, y: np.ndarray) -> Isotonic:
        order = np.argsort(raw, kind="stable")
        blocks: list[list[float]] = []  # sum, count, least raw, most raw
        for r, v in zip(raw[order].tolist(), y[order].tolist(), strict=True):
            blocks.append([v, 1, r, r])
            while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
                s, n, _, hi = blocks.pop()
                blocks[-1][0] += s
                blocks[-1][1] += n
                blocks[-1][3] = hi
        if blocks:
            self.at = np.array([v for b in blocks for v in (b[2], b[3])])
            self.share = np.array([b[0] / b[1] for b in blocks for _ in range(2)])
        return self

    def __call__(self, raw: np.ndarray) -> np.ndarray:
        # a thousandth of the raw probability keeps the order inside a pooled block
        return 0.999 * np.interp(raw, self.at, self.share) + 0.001 / (1 + np.exp(-raw))
