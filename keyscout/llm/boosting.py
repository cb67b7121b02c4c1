"""Gradient-boosted trees over binned features with logistic loss, and isotonic calibration."""

from __future__ import annotations

import numpy as np


class BoostedTrees:
    """Depth-limited trees grown on quantile bins by second-order gain."""

    def __init__(self, trees: int = 120, depth: int = 4, rate: float = 0.15, bins: int = 64, smooth: float = 1.0):
        self.trees, self.depth, self.rate, self.bins, self.smooth = trees, depth, rate, bins, smooth
        self.grown: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def _binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, x[:, j], "right") for j, c in enumerate(self.cuts)], 1).astype(np.int64)

    def fit(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> BoostedTrees:
        self.cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) for j in range(x.shape[1])]
        codes = self._binned(x)
        mean = np.clip(np.average(y, weights=w), 1e-3, 1 - 1e-3)
        self.start = float(np.log(mean / (1 - mean)))
        raw = np.full(len(y), self.start)
        for _ in range(self.trees):
            p = 1 / (1 + np.exp(-raw))
            tree = self._grow(codes, w * (p - y), w * p * (1 - p))
            self.grown.append(tree)
            raw += self.rate * self._apply(codes, tree)
        return self

    def _grow(self, codes, g, h):
        """Tree as heap arrays: feature (-1: leaf), cut bin, value."""
        size = 2 ** (self.depth + 1)
        feature, cut, value = np.full(size, -1), np.zeros(size, np.int64), np.zeros(size)
        node = np.ones(len(g), np.int64)
        width = self.bins + 1
        for level in range(self.depth + 1):
            first = 2**level
            live = node >= first
            at = node[live] - first
            value[first : 2 * first] = -np.bincount(at, g[live], first) / (np.bincount(at, h[live], first) + self.smooth)
            if level == self.depth or not live.any():
                break
            best = np.full(first, 1e-6)
            for j in range(codes.shape[1]):
                slot = at * width + codes[live, j]
                gs = np.bincount(slot, g[live], first * width).reshape(first, width).cumsum(1)
                hs = np.bincount(slot, h[live], first * width).reshape(first, width).cumsum(1)
                gt, ht = gs[:, -1:], hs[:, -1:]
                gain = gs**2 / (hs + self.smooth) + (gt - gs) ** 2 / (ht - hs + self.smooth) - gt**2 / (ht + self.smooth)
                gain[(hs < 1e-2) | (ht - hs < 1e-2)] = 0
                k = gain.argmax(1)
                top = gain[np.arange(first), k]
                better = top > best
                best[better], feature[first : 2 * first][better], cut[first : 2 * first][better] = top[better], j, k[better]
            split = live & (feature[node] >= 0)
            rows = np.flatnonzero(split)
            f = feature[node[rows]]
            node[rows] = 2 * node[rows] + (codes[rows, f] > cut[node[rows]])
        return feature, cut, value

    def _apply(self, codes, tree):
        feature, cut, value = tree
        node = np.ones(len(codes), np.int64)
        for _ in range(self.depth):
            f = feature[node]
            go = f >= 0
            if not go.any():
                break
            rows = np.flatnonzero(go)
            node[rows] = 2 * node[rows] + (codes[rows, f[rows]] > cut[node[rows]])
        return value[node]

    def raw(self, x: np.ndarray) -> np.ndarray:
        codes = self._binned(x)
        out = np.full(len(x), self.start)
        for tree in self.grown:
            out += self.rate * self._apply(codes, tree)
        return out


class Isotonic:
    """Weighted pool-adjacent-violators fit, read by linear interpolation between block centres."""

    def fit(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> Isotonic:
        order = np.argsort(x, kind="stable")
        blocks: list[list[float]] = []  # mean, weight, weighted x
        for a, b, c in zip(x[order], y[order], w[order]):
            blocks.append([b, c, a * c])
            while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
                m, n, s = blocks.pop()
                q = blocks[-1]
                q[0], q[1], q[2] = (q[0] * q[1] + m * n) / (q[1] + n), q[1] + n, q[2] + s
        self.at = np.array([s / n for _, n, s in blocks])
        self.value = np.array([m for m, _, _ in blocks])
        return self

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return np.interp(x, self.at, self.value) if len(self.at) else np.zeros(len(x))
