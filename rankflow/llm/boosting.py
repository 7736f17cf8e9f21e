"""Gradient-boosted trees for two classes, fitted on the driver to a bounded number of rows, and isotonic calibration.

A fitted model scores arrays, or turns into one SQL expression so that scoring stays in the JVM.
"""

from __future__ import annotations

import numpy as np


class Boosted:
    """Logistic loss, Newton leaf values, histogram splits at up to ``bins`` quantiles; deterministic."""

    def __init__(self, rounds: int = 40, depth: int = 3, rate: float = 0.2, bins: int = 32, ridge: float = 1.0, least: float = 2.0):
        self.rounds, self.depth, self.rate, self.bins, self.ridge, self.least = rounds, depth, rate, bins, ridge, least
        self.base, self.trees = 0.0, []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        x, y = np.asarray(x, float), np.asarray(y, float)
        if not len(y):
            return self
        share = min(max(y.mean(), 1e-4), 1 - 1e-4)
        self.base = float(np.log(share / (1 - share)))
        if y.min() == y.max():
            return self
        cuts = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        codes = np.stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T, strict=True)], 1)
        f = np.full(len(y), self.base)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-f))
            tree = self._grow(codes, cuts, y - p, p * (1 - p), np.arange(len(y)), self.depth)
            self.trees.append(tree)
            f += self._apply(tree, x)
        return self

    def _grow(self, codes, cuts, g, h, rows, depth):
        total_g, total_h = g[rows].sum(), h[rows].sum()
        leaf = float(self.rate * total_g / (total_h + self.ridge))
        if depth == 0 or len(rows) < 4:
            return leaf
        best = (1e-6, None, None)
        for k, c in enumerate(cuts):
            if not len(c):
                continue
            gs, hs = (np.cumsum(np.bincount(codes[rows, k], w[rows], len(c) + 1))[:-1] for w in (g, h))
            ok = (hs >= self.least) & (total_h - hs >= self.least)
            gain = np.where(ok, gs**2 / (hs + self.ridge) + (total_g - gs) ** 2 / (total_h - hs + self.ridge) - total_g**2 / (total_h + self.ridge), -1)
            at = int(np.argmax(gain))
            if gain[at] > best[0]:
                best = (gain[at], k, at)
        if best[1] is None:
            return leaf
        _, k, at = best
        left = codes[rows, k] <= at
        return k, float(cuts[k][at]), self._grow(codes, cuts, g, h, rows[left], depth - 1), self._grow(codes, cuts, g, h, rows[~left], depth - 1)

    def _apply(self, tree, x: np.ndarray) -> np.ndarray:
        if not isinstance(tree, tuple):
            return np.full(len(x), tree)
        k, cut, low, high = tree
        return np.where(x[:, k] <= cut, self._apply(low, x), self._apply(high, x))

    def score(self, x: np.ndarray) -> np.ndarray:
        """Log odds."""
        out = np.full(len(x), self.base)
        for t in self.trees:
            out += self._apply(t, x)
        return out

    def sql_text(self, features: list[str]) -> str:
        """SQL for the log odds from names of doubles."""

        def of(tree) -> str:
            if not isinstance(tree, tuple):
                return f"({tree!r}D)"
            return f"IF({features[tree[0]]} <= ({tree[1]!r}D), {of(tree[2])}, {of(tree[3])})"

        return " + ".join([f"({self.base!r}D)", *map(of, self.trees)])


class Isotonic:
    """Least squares under the order of scores (pool adjacent violators), linear between the pools' middles."""

    def fit(self, score: np.ndarray, y: np.ndarray) -> Isotonic:
        order = np.argsort(score, kind="stable")
        pools: list[list[float]] = []  # mean, weight, lowest score, highest score
        for s, v in zip(np.asarray(score, float)[order], np.asarray(y, float)[order], strict=True):
            if pools and pools[-1][3] == s:
                m, w, lo, _ = pools.pop()
                pools.append([(m * w + v) / (w + 1), w + 1, lo, s])
            else:
                pools.append([v, 1.0, s, s])
            while len(pools) > 1 and pools[-2][0] >= pools[-1][0]:
                m, w, _, hi = pools.pop()
                a = pools[-1]
                pools[-1] = [(a[0] * a[1] + m * w) / (a[1] + w), a[1] + w, a[2], hi]
        self.x = np.array([p for m, _, lo, hi in pools for p in ((lo, hi) if hi > lo else (lo,))] or [0.0])
        self.y = np.array([m for m, _, lo, hi in pools for _ in ((lo, hi) if hi > lo else (lo,))] or [0.0])
        return self

    def __call__(self, score: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(score, self.x, self.y), 0.0, 1.0)
