"""Gradient-boosted trees in numpy: histogram splits, monotonic constraints, flat nodes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class FlatTrees:
    """All trees as arrays of shape (trees, nodes); ``feature`` is -1 in a leaf."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    base: float
    depth: int

    def margin(self, x: np.ndarray) -> np.ndarray:
        """Sum of the leaf values over trees, for all rows and trees at once."""
        n, trees = len(x), len(self.feature)
        if not trees or not n:
            return np.full(n, self.base)
        at = np.zeros((n, trees), dtype=np.int64)
        rows, tree = np.arange(n)[:, None], np.arange(trees)[None, :]
        for _ in range(self.depth):
            f = self.feature[tree, at]
            go_left = x[rows, np.maximum(f, 0)] <= self.threshold[tree, at]
            at = np.where(f < 0, at, np.where(go_left, self.left[tree, at], self.right[tree, at]))
        return self.base + self.value[tree, at].sum(axis=1)

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.margin(x), -40, 40)))


def fit(
    x: np.ndarray,
    y: np.ndarray,
    monotone: np.ndarray,
    trees: int = 80,
    depth: int = 3,
    rate: float = 0.15,
    bins: int = 64,
    smooth: float = 1.0,
    least: int = 10,
) -> FlatTrees:
    """Logistic boosting. ``monotone``: -1, 0 or 1 per column. A split that breaks its
    column's direction is refused, and the middle of its two values bounds all
    values below it, so the sum of trees keeps the direction too."""
    n, width = x.shape
    share = np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3)
    base = float(np.log(share / (1 - share)))
    size = 2 ** (depth + 1) - 1
    shape = (trees, size)
    out = FlatTrees(
        np.full(shape, -1, np.int64), np.zeros(shape), np.zeros(shape, np.int64), np.zeros(shape, np.int64), np.zeros(shape), base, depth
    )
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    binned = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    margin = np.full(n, base)
    for t in range(trees):
        p = 1.0 / (1.0 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        stack = [(0, np.arange(n), 0, -np.inf, np.inf)]
        used = 1
        while stack:
            node, rows, level, low, high = stack.pop()
            gs, hs = g[rows].sum(), h[rows].sum()
            value = np.clip(-gs / (hs + smooth), low, high)
            best = None
            if level < depth and len(rows) >= 2 * least:
                whole = gs * gs / (hs + smooth)
                for f in range(width):
                    k = len(cuts[f])
                    if not k:
                        continue
                    b = binned[rows, f]
                    gl = np.cumsum(np.bincount(b, g[rows], k + 1))[:-1]
                    hl = np.cumsum(np.bincount(b, h[rows], k + 1))[:-1]
                    nl = np.cumsum(np.bincount(b, minlength=k + 1))[:-1]
                    wl = np.clip(-gl / (hl + smooth), low, high)
                    wr = np.clip(-(gs - gl) / (hs - hl + smooth), low, high)
                    gain = gl * gl / (hl + smooth) + (gs - gl) ** 2 / (hs - hl + smooth) - whole
                    fair = (nl >= least) & (len(rows) - nl >= least) & (monotone[f] * (wr - wl) >= 0)
                    gain = np.where(fair, gain, -1.0)
                    c = int(gain.argmax())
                    if gain[c] > 1e-6 and (best is None or gain[c] > best[0]):
                        best = (gain[c], f, c, wl[c], wr[c])
            if best is None:
                out.value[t, node] = rate * value
                margin[rows] += rate * value
                continue
            _, f, c, wl, wr = best
            goes = binned[rows, f] <= c
            out.feature[t, node], out.threshold[t, node] = f, cuts[f][c]
            out.left[t, node], out.right[t, node] = used, used + 1
            bounds = [(low, high), (low, high)]
            if monotone[f]:
                middle = (wl + wr) / 2
                bounds = [(low, middle), (middle, high)] if monotone[f] > 0 else [(middle, high), (low, middle)]
            stack.append((used, rows[goes], level + 1, *bounds[0]))
            stack.append((used + 1, rows[~goes], level + 1, *bounds[1]))
            used += 2
    return out
