"""Gradient-boosted regression trees with the logistic loss, on binned features in numpy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Trees:
    """Complete binary trees of equal depth; inner node k has the children 2k + 1 and 2k + 2."""

    base: float
    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray  # a value up to it goes left
    leaf: np.ndarray  # trees x leaves

    def margin(self, x: np.ndarray) -> np.ndarray:
        """Log odds of each row."""
        out, rows = np.full(len(x), self.base), np.arange(len(x))
        depth = int(np.log2(self.leaf.shape[1]))
        for feature, threshold, leaf in zip(self.feature, self.threshold, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(depth):
                node = 2 * node + 1 + (x[rows, feature[node]] > threshold[node])
            out += leaf[node - (1 << depth) + 1]
        return out


def train(x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 4, rate: float = 0.3, bins: int = 32, penalty: float = 1.0) -> Trees:
    """Fits trees one after another to the gradients, by histograms of quantile bins; deterministic."""
    n, width = x.shape
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for f in range(width)]
    binned = np.column_stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)])
    share = np.clip(y.mean(), 1e-6, 1 - 1e-6)
    base = float(np.log(share / (1 - share)))
    margin, inner = np.full(n, base), (1 << depth) - 1
    out = Trees(base, np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, inner + 1)))
    for t in range(trees):
        p = 1 / (1 + np.exp(-margin))
        slope, curve, node = y - p, p * (1 - p), np.zeros(n, np.int64)
        for level in range(depth):
            first, k = (1 << level) - 1, 1 << level
            at = node - first
            best = np.full(k, 1e-9)
            for f in range(width):
                cell = at * bins + binned[:, f]
                g, h = (np.cumsum(np.bincount(cell, v, k * bins).reshape(k, bins), axis=1) for v in (slope, curve))
                gain = g**2 / (h + penalty) + (g[:, -1:] - g) ** 2 / (h[:, -1:] - h + penalty) - g[:, -1:] ** 2 / (h[:, -1:] + penalty)
                gain = gain[:, : len(edges[f])]
                if gain.shape[1]:
                    cut = gain.argmax(axis=1)
                    for j in np.flatnonzero(gain[np.arange(k), cut] > best):
                        best[j] = gain[j, cut[j]]
                        out.feature[t, first + j], out.threshold[t, first + j] = f, edges[f][cut[j]]
            node = 2 * node + 1 + (x[np.arange(n), out.feature[t, node]] > out.threshold[t, node])
        leaf = node - inner
        out.leaf[t] = rate * np.bincount(leaf, slope, inner + 1) / (np.bincount(leaf, curve, inner + 1) + penalty)
        margin += out.leaf[t][leaf]
    return out
