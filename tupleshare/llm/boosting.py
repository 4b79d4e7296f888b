"""Histogram gradient boosting for two classes, in numpy; trees are complete and kept as arrays."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Forest:
    """Node n of a tree has the children 2n+1 and 2n+2; a row goes to the second if its feature exceeds the bound."""

    base: float
    feature: np.ndarray  # trees x (2^depth - 1)
    bound: np.ndarray
    leaf: np.ndarray  # trees x 2^depth

    def margin(self, x: np.ndarray, rows: int = 2048) -> np.ndarray:
        trees, inner = self.feature.shape
        out = np.full(len(x), self.base)
        tree = np.arange(trees)
        for at in range(0, len(x), rows):
            part = x[at : at + rows]
            node = np.zeros((len(part), trees), dtype=np.int64)
            line = np.arange(len(part))[:, None]
            for _ in range(inner.bit_length() if trees else 0):
                node = 2 * node + 1 + (part[line, self.feature[tree, node]] > self.bound[tree, node])
            out[at : at + rows] += self.leaf[tree, node - inner].sum(axis=1) if trees else 0.0
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x)))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 2.0, least: float = 1.0) -> Forest:
    """x: rows x features, finite; y: 0 or 1. Without rows of both classes the forest has no trees and scores the smoothed share of ones."""
    n, width = x.shape
    base = float(np.log((y.sum() + 1) / (n - y.sum() + 1)))
    inner = 2**depth - 1
    if not 0 < y.sum() < n:
        return Forest(base, np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)))
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    code = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    flat = code + np.arange(width) * bins
    margin = np.full(n, base)
    features, bounds, leaves = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = y - p, p * (1 - p)
        feature, bound = np.zeros(inner, np.int64), np.full(inner, np.inf)
        node = np.zeros(n, dtype=np.int64)  # within its level
        for level in range(depth):
            count = 2**level
            cell = (node[:, None] * (width * bins) + flat).ravel()
            sums = [np.bincount(cell, np.repeat(v, width), count * width * bins).reshape(count, width, bins).cumsum(axis=2) for v in (g, h)]
            (gl, hl), (gt, ht) = sums, (s[:, :1, -1:] for s in sums)
            gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
            gain[(hl < least) | (ht - hl < least)] = 0
            best = gain.reshape(count, -1).argmax(axis=1)
            at, cut = np.divmod(best, bins)
            split = np.zeros(count, np.int64)
            for k in range(count):
                c = cuts[at[k]]
                if gain[k, at[k], cut[k]] > 1e-9 and cut[k] < len(c):
                    feature[count - 1 + k], bound[count - 1 + k], split[k] = at[k], c[cut[k]], 1
            right = (x[np.arange(n), feature[count - 1 + node]] > bound[count - 1 + node]) & (split[node] == 1)
            node = 2 * node + right
        total_g, total_h = (np.bincount(node, v, inner + 1) for v in (g, h))
        leaf = rate * total_g / (total_h + ridge)
        margin += leaf[node]
        features.append(feature)
        bounds.append(bound)
        leaves.append(leaf)
    return Forest(base, np.stack(features), np.stack(bounds), np.stack(leaves))
