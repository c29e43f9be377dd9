"""A random forest for two classes, grown in numpy and written out as a SQL expression."""

from __future__ import annotations

import numpy as np


class Forest:
    """Trees on bootstrap samples, each split chosen by Gini gain among a random third of the features. Leaves hold the share of positives."""

    def __init__(self, names: list[str], trees: int = 15, depth: int = 6, least: int = 3, seed: int = 9) -> None:
        self.names, self.trees, self.depth, self.least, self.seed = names, trees, depth, least, seed
        self.roots: list = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Forest:
        rng = np.random.default_rng(self.seed)
        cuts = [np.unique(np.quantile(x[:, f], np.linspace(0.02, 0.98, 25))) for f in range(x.shape[1])]
        self.roots = []
        for _ in range(self.trees):
            rows = rng.integers(0, len(y), len(y))
            self.roots.append(self._grow(x[rows], y[rows], cuts, rng, 0))
        return self

    def _grow(self, x: np.ndarray, y: np.ndarray, cuts: list[np.ndarray], rng: np.random.Generator, level: int):
        share = float(y.mean())
        if level == self.depth or len(y) < 2 * self.least or share in (0.0, 1.0):
            return share
        best = (1e-9, None, 0.0)
        for f in rng.permutation(x.shape[1])[: max(2, x.shape[1] // 3)]:
            for c in cuts[f]:
                left = x[:, f] <= c
                n = int(left.sum())
                if self.least <= n <= len(y) - self.least:
                    a, b = y[left].mean(), y[~left].mean()
                    gain = share * (1 - share) - (n * a * (1 - a) + (len(y) - n) * b * (1 - b)) / len(y)
                    if gain > best[0]:
                        best = (gain, int(f), float(c))
        if best[1] is None:
            return share
        left = x[:, best[1]] <= best[2]
        return best[1], best[2], self._grow(x[left], y[left], cuts, rng, level + 1), self._grow(x[~left], y[~left], cuts, rng, level + 1)

    def predict(self, x: np.ndarray) -> np.ndarray:
        def walk(node, row):
            while isinstance(node, tuple):
                node = node[2] if row[node[0]] <= node[1] else node[3]
            return node

        return np.array([np.mean([walk(r, row) for r in self.roots]) for row in x])

    def sql(self, prefix: str) -> str:
        """The mean of the trees as an expression over fields `prefix`.name."""

        def write(node) -> str:
            if not isinstance(node, tuple):
                return f"{node:.6f}D"
            return f"CASE WHEN {prefix}.{self.names[node[0]]} <= {node[1]!r}D THEN {write(node[2])} ELSE {write(node[3])} END"

        return "(" + " + ".join(write(r) for r in self.roots) + f") / {len(self.roots)}.0D"
