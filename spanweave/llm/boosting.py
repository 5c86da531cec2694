"""Histogram gradient-boosted trees for a binary label.

``fit`` bins each feature at quantiles, then grows every tree level by level on gradient
histograms. A tree of depth D is kept as a complete binary tree in flat arrays
(``feature``, ``threshold`` of 2^D - 1 nodes, ``leaf`` of 2^D values), so ``margin`` walks all
rows and trees at once with numpy, and ``as_column`` writes the same trees as CASE expressions.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass
class Forest:
    feature: np.ndarray  # trees x (2^depth - 1)
    threshold: np.ndarray  # goes right where value > threshold
    leaf: np.ndarray  # trees x 2^depth
    base: float
    depth: int

    def margin(self, x: np.ndarray) -> np.ndarray:
        """Log-odds of each row."""
        total = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for t in range(len(self.feature)):
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                at = 2 * at + 1 + (x[rows, self.feature[t, at]] > self.threshold[t, at])
            total += self.leaf[t, at - (2**self.depth - 1)]
        return total

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.margin(x), -40, 40)))

    def as_column(self, names: list[str]) -> Column:
        """The probability as a DataFrame expression over the feature columns ``names``."""

        def node(t: int, at: int) -> Column:
            if at >= 2**self.depth - 1:
                return F.lit(float(self.leaf[t, at - (2**self.depth - 1)]))
            left, right = node(t, 2 * at + 1), node(t, 2 * at + 2)
            if not np.isfinite(self.threshold[t, at]):
                return left
            return F.when(F.col(names[self.feature[t, at]]) > F.lit(float(self.threshold[t, at])), right).otherwise(left)

        margin = F.lit(float(self.base))
        for t in range(len(self.feature)):
            margin = margin + node(t, 0)
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-F.greatest(F.lit(-40.0), F.least(F.lit(40.0), margin))))


def fit(x: np.ndarray, y: np.ndarray, *, trees: int = 60, depth: int = 4, rate: float = 0.2, bins: int = 64, ridge: float = 1.0, least: float = 2.0) -> Forest:
    """Boost ``trees`` trees on the logistic loss. No rows, or one class only: a constant forest (0.5 with no rows)."""
    n, width = x.shape
    y = y.astype(np.float64)
    inner, leaves = 2**depth - 1, 2**depth
    rate_one = (y.sum() + 0.5) / (n + 1.0)
    base = float(np.log(rate_one / (1 - rate_one)))
    if n == 0 or y.min() == y.max() or width == 0:
        return Forest(np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, leaves)), base, depth)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], 1)
    slot = binned + np.arange(width) * bins
    margin = np.full(n, base)
    out_f, out_t, out_l = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, leaves))
    for t in range(trees):
        p = 1.0 / (1.0 + np.exp(-margin))
        grad, hess = p - y, np.maximum(p * (1 - p), 1e-9)
        at = np.zeros(n, np.int64)
        for level in range(depth):
            first, count = 2**level - 1, 2**level
            key = ((at - first)[:, None] * (width * bins) + slot).ravel()
            shape = (count, width, bins)
            g = np.bincount(key, np.repeat(grad, width), count * width * bins).reshape(shape)
            h = np.bincount(key, np.repeat(hess, width), count * width * bins).reshape(shape)
            gl, hl = g.cumsum(2), h.cumsum(2)
            gt, ht = gl[:, :, -1:], hl[:, :, -1:]
            gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
            gain[(hl < least) | (ht - hl < least)] = 0
            gain[:, :, -1] = 0
            best = gain.reshape(count, -1).argmax(1)
            for k in range(count):
                j, b = divmod(int(best[k]), bins)
                if gain[k, j, b] > 1e-9 and b < len(edges[j]):
                    out_f[t, first + k], out_t[t, first + k] = j, edges[j][b]
            at = 2 * at + 1 + (x[np.arange(n), out_f[t, at]] > out_t[t, at])
        at -= inner
        out_l[t] = -rate * np.bincount(at, grad, leaves) / (np.bincount(at, hess, leaves) + ridge)
        margin += out_l[t, at]
    return Forest(out_f, out_t, out_l, base, depth)
