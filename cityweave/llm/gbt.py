"""Gradient-boosted trees with monotonic constraints, flattened for vectorised scoring."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class FlatTrees:
    """Nodes of all trees in arrays: leaves point at themselves, so every row takes `depth` steps."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    depth: int
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for each row."""
        total = np.full(len(x), self.prior)
        rows = np.arange(len(x))
        for root in self.roots:
            node = np.full(len(x), root)
            for _ in range(self.depth):
                node = np.where(x[rows, self.feature[node]] <= self.threshold[node], self.left[node], self.right[node])
            total += self.value[node]
        return 1 / (1 + np.exp(-total))


def fit(x: np.ndarray, y: np.ndarray, decreasing: list[int] = (), trees: int = 60, depth: int = 3, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, least: int = 10) -> FlatTrees:
    """Logistic boosting over histograms; features in `decreasing` never raise the score as they grow.

    A split on a constrained feature is taken only if its children's values fall
    in order, and the midpoint between them bounds all that is grown below.
    """
    n, width = x.shape
    if not n:  # nothing to learn from: everything scores a half
        none = np.zeros(0, np.int64)
        return FlatTrees(none, np.zeros(0), none, none, np.zeros(0), none, depth, 0.0)
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(width)]
    binned = np.stack([np.searchsorted(edges[f], x[:, f], "left") for f in range(width)], axis=1)
    share = min(max(y.mean(), 1e-6), 1 - 1e-6)
    prior = float(np.log(share / (1 - share)))
    total = np.full(n, prior)
    nodes: list[list] = []
    roots = []

    def leaf(g: float, h: float, low: float, high: float) -> float:
        return float(np.clip(-g / (h + ridge), low, high))

    def grow(rows: np.ndarray, level: int, low: float, high: float) -> int:
        me = len(nodes)
        g, h = grad[rows].sum(), hess[rows].sum()
        nodes.append([0, np.inf, me, me, rate * leaf(g, h, low, high)])
        if level == depth or len(rows) < 2 * least:
            total[rows] += nodes[me][4]
            return me
        best = (1e-6, None)
        for f in range(width):
            if not len(edges[f]):
                continue
            m = len(edges[f]) + 1
            cg, ch, cn = (np.cumsum(np.bincount(binned[rows, f], w, m))[:-1] for w in (grad[rows], hess[rows], None))
            ok = (cn >= least) & (len(rows) - cn >= least)
            vl, vr = np.clip(-cg / (ch + ridge), low, high), np.clip(-(g - cg) / (h - ch + ridge), low, high)
            if f in decreasing:
                ok &= vl >= vr
            gain = np.where(ok, cg**2 / (ch + ridge) + (g - cg) ** 2 / (h - ch + ridge) - g**2 / (h + ridge), 0)
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], (f, k, vl[k], vr[k]))
        if best[1] is None:
            total[rows] += nodes[me][4]
            return me
        f, k, vl, vr = best[1]
        middle = (vl + vr) / 2
        goes = binned[rows, f] <= k
        nodes[me][0], nodes[me][1] = f, edges[f][k]
        nodes[me][2] = grow(rows[goes], level + 1, middle if f in decreasing else low, high)
        nodes[me][3] = grow(rows[~goes], level + 1, low, middle if f in decreasing else high)
        return me

    for _ in range(trees):
        p = 1 / (1 + np.exp(-total))
        grad, hess = p - y, p * (1 - p)
        roots.append(grow(np.arange(n), 0, -np.inf, np.inf))
    return FlatTrees(*(np.array(c, t) for c, t in zip(zip(*nodes, strict=True), (np.int64, float, np.int64, np.int64, float), strict=True)), np.array(roots, np.int64), depth, prior)
