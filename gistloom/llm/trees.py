"""Histogram gradient-boosted trees in numpy, flattened into arrays for vectorised traversal."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Forest:
    """Node k tests ``x[feature] <= cut``; children are 2k+1 and 2k+2 of complete trees."""

    feature: np.ndarray  # (trees, inner nodes)
    cut: np.ndarray
    value: np.ndarray  # (trees, leaves)
    base: float
    depth: int

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for f, c, v in zip(self.feature, self.cut, self.value, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + (x[rows, f[node]] > c[node])
            out += v[node - len(f)]
        return out

    def proba(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -30, 30))) if len(x) else np.zeros(0)


def fit(x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, l2: float = 2.0, min_rows: int = 5) -> Forest:
    """Logistic loss, level-wise growth; one class only gives a constant forest."""
    n, width = x.shape
    inner, leaves = 2**depth - 1, 2**depth
    share = (y.sum() + 1) / (n + 2)
    base = float(np.log(share / (1 - share)))
    if n == 0 or y.min() == y.max():
        return Forest(np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, leaves)), base, depth)
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    binned = np.stack([np.searchsorted(c, x[:, j], "left") for j, c in enumerate(cuts)], 1)
    score = np.full(n, base)
    feats, thresholds, values = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-score))
        g, h = p - y, p * (1 - p)
        node = np.zeros(n, np.int64)
        feature, cut = np.zeros(inner, np.int64), np.full(inner, np.inf)
        for level in range(depth):
            first, count = 2**level - 1, 2**level
            local = node - first
            best = np.full(count, 1e-6)
            pick = np.full((count, 2), -1)
            for j in range(width):
                if not len(cuts[j]):
                    continue
                slots = bins + 1
                code = local * slots + binned[:, j]
                gs, hs, cs = (np.bincount(code, w, count * slots).reshape(count, slots) for w in (g, h, None))
                gl, hl, cl = gs.cumsum(1)[:, :-1], hs.cumsum(1)[:, :-1], cs.cumsum(1)[:, :-1]
                gt, ht, ct = gs.sum(1)[:, None], hs.sum(1)[:, None], cs.sum(1)[:, None]
                gain = gl**2 / (hl + l2) + (gt - gl) ** 2 / (ht - hl + l2) - gt**2 / (ht + l2)
                gain[(cl < min_rows) | (ct - cl < min_rows)] = 0
                gain = gain[:, : len(cuts[j])]
                at = gain.argmax(1)
                top = gain[np.arange(count), at]
                better = top > best
                best[better] = top[better]
                pick[better] = np.stack([np.full(count, j), at], 1)[better]
            for k in range(count):
                if pick[k, 0] >= 0:
                    feature[first + k], cut[first + k] = pick[k, 0], cuts[pick[k, 0]][pick[k, 1]]
            node = 2 * node + 1 + (x[np.arange(n), feature[node]] > cut[node])
        leaf = node - inner
        value = -rate * np.bincount(leaf, g, leaves) / (np.bincount(leaf, h, leaves) + l2)
        score += value[leaf]
        feats.append(feature)
        thresholds.append(cut)
        values.append(value)
    return Forest(np.array(feats), np.array(thresholds), np.array(values), base, depth)
