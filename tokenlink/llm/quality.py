"""Quality scores from a generalised additive model with pairwise interactions.

Text features are computed inside the plan.  On the driver a bounded sample of labelled rows
(``max_train_rows``, taken by the hash of the id) is binned, and shallow trees are boosted cyclically, one
feature a step, then one pair of features a step; every tree only adds to a lookup table by bin.  A score is
the sum of table entries passed through the logistic function, computed for Arrow batches by array indexing.

Labels are learnt only from rows whose ``crc32(doc_id) % 4`` is not 2.  Language, source, id and labels are
never features.

Defined results.  A null or empty text is scored like any other, from zero features.  Without labels of both
kinds the score is the smoothed share of good labels (0.5 if there are none).  A label's id met in several
documents labels each; null ids and null labels label nothing; repeated rows are scored alike.  A very long text is
read whole.  An empty table gives no rows.  Further columns pass through; columns named ``score`` or ``predicted``
are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .rules import SPACE

HELD_OUT, THRESHOLD = 2, 0.7


def fold(id_col: str = "doc_id") -> Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 4


def features(text: Column) -> dict[str, Column]:
    t = F.coalesce(text, F.lit(""))
    size = F.length(t)
    less = lambda s: (size - F.length(F.replace(t, F.lit(s), F.lit("")))).cast("double")
    count = lambda p: F.regexp_count(t, F.lit(p)).cast("double")
    trimmed = F.trim(t, F.lit(SPACE))
    words = F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, r"[\x20\x09-\x0D]+", -1))
    lines = F.split(t, "\n", -1)
    return {
        "words": F.size(words).cast("double"),
        "distinct": F.size(F.array_distinct(words)).cast("double"),
        "chars": size.cast("double"),
        "bytes": F.octet_length(t).cast("double"),
        "lines": F.size(lines).cast("double"),
        "distinct_lines": F.size(F.array_distinct(lines)).cast("double"),
        "symbols": count(r"[#*$%&<>{}\\^~=_]"),
        "bars": less("|"),
        "bangs": less("!"),
        "stops": less("."),
        "commas": less(","),
        "upper": count("[A-Z]"),
        "digits": count("[0-9]"),
    }


def _ratios(raw: pd.DataFrame) -> np.ndarray:
    """Scale-free features from the counts."""
    c = {k: raw[k].to_numpy(float) for k in raw}
    n, size, lines = np.maximum(c["words"], 1), np.maximum(c["chars"], 1), np.maximum(c["lines"], 1)
    expected = np.sqrt(n)  # a repetitive text has few distinct words for its length
    return np.column_stack([
        np.log1p(c["words"]), c["distinct"] / n, (c["distinct"] - expected) / n, size / n, c["bytes"] / size, n / lines, c["distinct_lines"] / lines,
        c["symbols"] / n, c["bars"] / n, c["bangs"] / n, c["stops"] / n, c["commas"] / n, c["upper"] / size, c["digits"] / size,
    ])


@dataclass
class Additive:
    """Lookup tables by bin for single features and for pairs."""

    bins: int = 32
    pair_bins: int = 8
    n_pairs: int = 6
    rounds: int = 60
    rate: float = 0.2
    l2: float = 2.0
    bias: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)
    shapes: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int]] = field(default_factory=list)
    surfaces: list[np.ndarray] = field(default_factory=list)

    def _tree(self, g: np.ndarray, h: np.ndarray, leaves: int = 3) -> np.ndarray:
        """A shallow tree over ordered bins, given sums of gradients and curvatures: the step for each bin."""
        spans, value = [(0, len(g))], lambda a, b: g[a:b].sum() ** 2 / (h[a:b].sum() + self.l2)
        while len(spans) < leaves:
            best = max(((value(a, c) + value(c, b) - value(a, b), k, c) for k, (a, b) in enumerate(spans) for c in range(a + 1, b)), default=None)
            if best is None or best[0] <= 1e-9:
                break
            a, b = spans.pop(best[1])
            spans += [(a, best[2]), (best[2], b)]
        out = np.zeros(len(g))
        for a, b in spans:
            out[a:b] = self.rate * g[a:b].sum() / (h[a:b].sum() + self.l2)
        return out

    def fit(self, x: np.ndarray, y: np.ndarray) -> Additive:
        p = (y.sum() + 1) / (len(y) + 2)
        self.bias = float(np.log(p / (1 - p)))
        cut = lambda v, k: np.unique(np.quantile(v, np.linspace(0, 1, k + 1)[1:-1]))
        if len(y) == 0 or y.min() == y.max():
            return self
        self.edges = [cut(v, self.bins) for v in x.T]
        self.coarse = [cut(v, self.pair_bins) for v in x.T]
        self.shapes = [np.zeros(len(e) + 1) for e in self.edges]
        fine, wide = self._binned(x, self.edges), self._binned(x, self.coarse)
        margin = np.full(len(y), self.bias)

        def slopes() -> tuple[np.ndarray, np.ndarray]:
            q = 1 / (1 + np.exp(-margin))
            return y - q, q * (1 - q)

        for _ in range(self.rounds):
            for j, b in enumerate(fine):
                g, h = slopes()
                k = len(self.shapes[j])
                step = self._tree(np.bincount(b, g, k), np.bincount(b, h, k))
                self.shapes[j] += step
                margin += step[b]
        cell = lambda i, j: wide[i] * (len(self.coarse[j]) + 1) + wide[j]
        cells = lambda i, j: (len(self.coarse[i]) + 1) * (len(self.coarse[j]) + 1)
        g, h = slopes()

        def gain(i: int, j: int) -> float:
            a, b = np.bincount(cell(i, j), g, cells(i, j)), np.bincount(cell(i, j), h, cells(i, j))
            return float((a * a / (b + self.l2)).sum())

        ranked = sorted(((gain(i, j), i, j) for i in range(len(fine)) for j in range(i)), reverse=True)
        self.pairs = [(i, j) for _, i, j in ranked[: self.n_pairs]]
        self.surfaces = [np.zeros(cells(i, j)) for i, j in self.pairs]
        for _ in range(self.rounds // 3):
            for k, (i, j) in enumerate(self.pairs):
                g, h = slopes()
                c, n = cell(i, j), len(self.surfaces[k])
                a, b = np.bincount(c, g, n), np.bincount(c, h, n)
                rows = (len(self.coarse[i]) + 1, len(self.coarse[j]) + 1)
                # one cut along each feature: a tree of depth two on the grid
                first = self._tree(a.reshape(rows).sum(1), b.reshape(rows).sum(1), 2)
                step = np.empty(rows)
                for v in np.unique(first):
                    part = first == v
                    step[part] = self._tree(a.reshape(rows)[part].sum(0), b.reshape(rows)[part].sum(0), 2)
                self.surfaces[k] += step.ravel()
                margin += step.ravel()[c]
        return self

    @staticmethod
    def _binned(x: np.ndarray, edges: list[np.ndarray]) -> list[np.ndarray]:
        return [np.searchsorted(e, v, side="right") for e, v in zip(edges, x.T, strict=True)]

    def score(self, x: np.ndarray) -> np.ndarray:
        margin = np.full(len(x), self.bias)
        if self.edges:
            for shape, b in zip(self.shapes, self._binned(x, self.edges), strict=True):
                margin += shape[b]
            wide = self._binned(x, self.coarse)
            for (i, j), surface in zip(self.pairs, self.surfaces, strict=True):
                margin += surface[wide[i] * (len(self.coarse[j]) + 1) + wide[j]]
        return 1 / (1 + np.exp(-margin))


def train(docs: DataFrame, labels: DataFrame, max_train_rows: int = 20_000, id_col: str = "doc_id", text_col: str = "text") -> Additive:
    """Fit on at most ``max_train_rows`` labelled documents outside the held-out fold."""
    usable = labels.where((fold(id_col) != HELD_OUT) & F.col("quality").isNotNull()).select(F.col(id_col).alias("__id"), "quality")
    sample = usable.orderBy(F.xxhash64("__id"), "__id", "quality").limit(max_train_rows)  # so many rows at most are broadcast
    rows = docs.join(F.broadcast(sample), F.col(id_col) == F.col("__id")).select("quality", F.struct(*[v.alias(k) for k, v in features(F.col(text_col)).items()]).alias("f"))
    got = rows.select("quality", "f.*").limit(2 * max_train_rows).toPandas()
    got = got.sort_values(list(got.columns), kind="stable")  # arrival order must not matter
    return Additive().fit(_ratios(got.drop(columns="quality")), got["quality"].to_numpy(float))


def scored(docs: DataFrame, model: Additive, text_col: str = "text") -> DataFrame:
    """``docs`` with ``score``."""

    @F.pandas_udf("double")
    def total(batches: Iterator[pd.DataFrame]) -> Iterator[pd.Series]:
        for raw in batches:
            yield pd.Series(model.score(_ratios(raw)))

    return docs.withColumn("score", total(F.struct(*[v.alias(k) for k, v in features(F.col(text_col)).items()])))


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with ``score`` and ``predicted`` (1 from ``THRESHOLD`` on)."""
    return scored(docs, train(docs, labels, id_col=id_col, text_col=text_col), text_col).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))
