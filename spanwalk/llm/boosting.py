"""Gradient-boosted trees of fixed depth for two classes, in NumPy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Boosted:
    """Complete trees: row t of `feature` and `cut` has the 2**depth - 1 splits, of `leaf` the values."""

    feature: np.ndarray
    cut: np.ndarray
    leaf: np.ndarray
    base: float

    def logit(self, x: np.ndarray) -> np.ndarray:
        out, rows = np.full(len(x), self.base), np.arange(len(x))
        depth = int(np.log2(self.leaf.shape[1]))
        for feature, cut, leaf in zip(self.feature, self.cut, self.leaf):
            at = np.zeros(len(x), dtype=np.int64)
            for _ in range(depth):
                at = 2 * at + 1 + (x[rows, feature[at]] > cut[at])
            out += leaf[at - (len(feature))]
        return out


def fit(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, trees: int = 120, depth: int = 4, rate: float = 0.25, bins: int = 24, ridge: float = 2.0, share: float = 0.3, seed: int = 5) -> Boosted:
    """Logistic loss, each tree on a drawn share of the rows, splits from histograms over quantile bins; deterministic."""
    n, width = x.shape
    weight = np.ones(n) if weight is None else weight
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    binned = np.stack([np.searchsorted(cuts[f], x[:, f], side="left") for f in range(width)], axis=1)
    base = float(np.log((weight @ y + 1) / (weight @ (1 - y) + 1)))
    score, inner = np.full(n, base), 2**depth - 1
    features, values, leaves = [], [], []
    dice = np.random.default_rng(seed)
    for _ in range(trees):
        rows = np.flatnonzero(dice.random(n) < share)
        if not len(rows):
            rows = np.arange(n)
        p = 1 / (1 + np.exp(-score[rows]))
        g, h = weight[rows] * (y[rows] - p), weight[rows] * p * (1 - p)
        own_bins, own_x = np.ascontiguousarray(binned[rows].T), x[rows]
        at = np.zeros(len(rows), dtype=np.int64)
        feature, cut = np.zeros(inner, dtype=np.int64), np.full(inner, np.inf)
        for level in range(depth):
            first, count = 2**level - 1, 2**level
            best = np.zeros(count)
            edge = np.full(count, bins)
            for f in range(width):
                k = (at - first) * bins + own_bins[f]
                sg = np.bincount(k, g, count * bins).reshape(count, bins).cumsum(axis=1)
                sh = np.bincount(k, h, count * bins).reshape(count, bins).cumsum(axis=1)
                tg, th = sg[:, -1:], sh[:, -1:]
                gain = sg**2 / (sh + ridge) + (tg - sg) ** 2 / (th - sh + ridge) - tg**2 / (th + ridge)
                gain[:, len(cuts[f]) :] = 0
                b = gain.argmax(axis=1)
                v = gain[np.arange(count), b]
                better = v > best + 1e-9
                best = np.where(better, v, best)
                edge = np.where(better, b, edge)
                feature[first : first + count][better] = f
            for c in range(count):
                if edge[c] < bins:
                    cut[first + c] = cuts[feature[first + c]][edge[c]]
            at = 2 * at + 1 + (own_x[np.arange(len(rows)), feature[at]] > cut[at])
        own = at - inner
        leaf = rate * np.bincount(own, g, inner + 1) / (np.bincount(own, h, inner + 1) + ridge)
        score += Boosted(feature[None], cut[None], leaf[None], 0.0).logit(x)
        features.append(feature)
        values.append(cut)
        leaves.append(leaf)
    return Boosted(np.stack(features), np.stack(values), np.stack(leaves), base)
