"""Gradient-boosted regression trees for two classes, in numpy."""

from __future__ import annotations

import numpy as np

from tricount.llm.nets import platt, sigmoid


class BoostedTrees:
    """Depth-limited trees on quantile thresholds, fitted to the gradient of the logistic loss; leaf values by Newton steps."""

    def __init__(self, trees: int = 40, depth: int = 3, rate: float = 0.2, ridge: float = 1.0, least: int = 8) -> None:
        self.trees, self.depth, self.rate, self.ridge, self.least = trees, depth, rate, ridge, least
        self.split = np.zeros((trees, 2**depth - 1), dtype=np.int64)  # features of inner nodes, in heap order
        self.cut = np.full((trees, 2**depth - 1), np.inf)
        self.leaf = np.zeros((trees, 2**depth))
        self.base, self.curve = 0.0, (1.0, 0.0)

    def _grow(self, x: np.ndarray, cuts: list[np.ndarray], g: np.ndarray, h: np.ndarray, tree: int) -> None:
        gain = lambda gs, hs: gs * gs / (hs + self.ridge)
        node = np.zeros(len(x), dtype=np.int64)
        for level in range(self.depth):
            for k in range(2**level - 1, 2 ** (level + 1) - 1):
                rows = np.flatnonzero(node == k)
                best = (1e-6, 0, np.inf)
                if len(rows) >= 2 * self.least:
                    whole = gain(g[rows].sum(), h[rows].sum())
                    for f, at in enumerate(cuts):
                        for c in at:
                            left = x[rows, f] <= c
                            n = int(left.sum())
                            if self.least <= n <= len(rows) - self.least:
                                gl, hl = g[rows][left].sum(), h[rows][left].sum()
                                won = gain(gl, hl) + gain(g[rows].sum() - gl, h[rows].sum() - hl) - whole
                                if won > best[0]:
                                    best = (won, f, c)
                self.split[tree, k], self.cut[tree, k] = best[1], best[2]
                node[rows] = 2 * k + 1 + (x[rows, best[1]] > best[2])
        node -= 2**self.depth - 1
        top = np.bincount(node, weights=g, minlength=2**self.depth)
        low = np.bincount(node, weights=h, minlength=2**self.depth)
        self.leaf[tree] = -self.rate * top / (low + self.ridge)

    def fit(self, x: np.ndarray, y: np.ndarray, hold: np.ndarray) -> BoostedTrees:
        """Grows on rows outside `hold`, calibrates on those in it."""
        xt, yt = x[~hold], y[~hold]
        share = np.clip(yt.mean(), 1e-3, 1 - 1e-3)
        self.base = float(np.log(share / (1 - share)))
        cuts = [np.unique(np.quantile(xt[:, f], np.linspace(0.05, 0.95, 13))) for f in range(x.shape[1])]
        f = np.full(len(xt), self.base)
        for t in range(self.trees):
            p = sigmoid(f)
            self._grow(xt, cuts, p - yt, p * (1 - p) + 1e-6, t)
            f += self._values(xt, t)
        self.curve = platt(self.margin(x[hold]), y[hold])
        return self

    def _values(self, x: np.ndarray, tree: int) -> np.ndarray:
        node = np.zeros(len(x), dtype=np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (x[np.arange(len(x)), self.split[tree, node]] > self.cut[tree, node])
        return self.leaf[tree, node - (2**self.depth - 1)]

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.base + sum(self._values(x, t) for t in range(self.trees))

    def probability(self, x: np.ndarray) -> np.ndarray:
        return sigmoid(self.curve[0] * self.margin(x) + self.curve[1])
