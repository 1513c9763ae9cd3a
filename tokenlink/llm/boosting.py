"""A small gradient-boosting fitter for the driver, and its trees as Spark expressions.

It serves fixed-size training sets (thousands of rows); scoring runs inside the plan.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


class Booster:
    """Logistic boosting with depth-two regression trees."""

    def __init__(self, rounds: int = 40, rate: float = 0.3, l2: float = 1.0):
        self.rounds, self.rate, self.l2 = rounds, rate, l2
        self.bias, self.trees = 0.0, []
        self.scale, self.shift = 1.0, 0.0  # Platt scaling

    def _split(self, x: np.ndarray, g: np.ndarray, h: np.ndarray) -> tuple | None:
        best = None
        for j in range(x.shape[1]):
            cuts = np.unique(x[:, j])
            for c in ((cuts[1:] + cuts[:-1]) / 2)[:: max(1, len(cuts) // 24)]:
                left = x[:, j] <= c
                gl, hl, gr, hr = g[left].sum(), h[left].sum(), g[~left].sum(), h[~left].sum()
                gain = gl * gl / (hl + self.l2) + gr * gr / (hr + self.l2)
                if best is None or gain > best[0] + 1e-12:
                    best = (gain, j, float(c))
        return best

    def _leaf(self, g: np.ndarray, h: np.ndarray) -> float:
        return float(self.rate * g.sum() / (h.sum() + self.l2))

    def fit(self, x: np.ndarray, y: np.ndarray) -> Booster:
        p = min(max(y.mean(), 1e-3), 1 - 1e-3)
        self.bias = math.log(p / (1 - p))
        for _ in range(self.rounds):
            q = 1 / (1 + np.exp(-self.margin(x)))
            g, h = y - q, q * (1 - q)
            if (top := self._split(x, g, h)) is None:
                break
            _, j, c = top
            sides = []
            for side in (x[:, j] <= c, x[:, j] > c):
                sub = self._split(x[side], g[side], h[side]) if side.sum() > 4 else None
                if sub is None:
                    sides.append((0, math.inf, self._leaf(g[side], h[side]), 0.0))
                else:
                    low = x[:, sub[1]] <= sub[2]
                    sides.append((sub[1], sub[2], self._leaf(g[side & low], h[side & low]), self._leaf(g[side & ~low], h[side & ~low])))
            self.trees.append((j, c, *sides))
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.bias)
        for j, c, a, b in self.trees:
            leaf = lambda s: np.where(x[:, s[0]] <= s[1], s[2], s[3])
            out += np.where(x[:, j] <= c, leaf(a), leaf(b))
        return out

    def calibrate(self, x: np.ndarray, y: np.ndarray, steps: int = 400) -> Booster:
        m = self.margin(x)
        for _ in range(steps):
            e = y - 1 / (1 + np.exp(-(self.scale * m + self.shift)))
            self.scale += 0.5 * float((e * m).mean()) / max(1.0, float((m * m).mean()))
            self.shift += 0.5 * float(e.mean())
        return self

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.scale * self.margin(x) + self.shift)))

    def column(self, features: Column) -> Column:
        """The calibrated probability; ``features`` is an array of doubles."""
        at = lambda j: F.get(features, F.lit(j))

        def leaf(s: tuple) -> Column:
            return F.lit(s[2]) if s[1] == math.inf else F.when(at(s[0]) <= s[1], F.lit(s[2])).otherwise(F.lit(s[3]))

        m = F.lit(self.bias)
        for j, c, a, b in self.trees:
            m = m + F.when(at(j) <= c, leaf(a)).otherwise(leaf(b))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-(m * self.scale + self.shift)))
