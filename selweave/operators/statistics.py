"""Compact statistics fitted to a budget of bytes, and asked on the driver for whole logs at once.

Every model has ``estimate(q)`` (rows of each query) and ``size_bytes()``. What
reaches the driver is the model itself: a dictionary's frequencies cut to the
budget, grid cells, or kept coefficients.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .baselines import grid_histogram, haar_coefficients, haar_top
from .query import Queries
from .relation import Dictionary


class ColumnStatistics:
    """Common values of each attribute with their shares, an equal-depth histogram of the others, attributes independent."""

    def __init__(self, shares: list[np.ndarray], numbers: int, rows: int) -> None:
        self.before = [np.concatenate([[0.0], np.cumsum(s)]) for s in shares]
        self.numbers, self.rows = numbers, rows

    @classmethod
    def fit(cls, dic: Dictionary, budget_bytes: int = 8_000, common: float = 0.5) -> "ColumnStatistics":
        """Half of an attribute's part of the budget holds common values (12 bytes), half buckets (12 bytes)."""
        per = max(2, budget_bytes // (12 * max(1, len(dic.attrs))))
        shares, numbers = [], 0
        for a in dic.attrs:
            f = np.array([x for _, x in dic.values(a)], float)
            top = np.argsort(-f, kind="stable")[: max(1, int(per * common))]
            rest = np.ones(len(f), bool)
            rest[top] = False
            own, numbers = np.zeros(len(f)), numbers + len(top)
            own[top] = f[top]
            left = np.flatnonzero(rest)
            if len(left):
                cum = np.cumsum(f[left]) - f[left]
                bucket = np.minimum((cum * (per - len(top)) / max(f[left].sum(), 1)).astype(int), max(1, per - len(top)) - 1)
                _, bucket = np.unique(bucket, return_inverse=True)
                own[left] = (np.bincount(bucket, f[left]) / np.bincount(bucket))[bucket]
                numbers += int(bucket.max()) + 1
            shares.append(own / max(f.sum(), 1))
        return cls(shares, numbers, dic.rows)

    def shares_of(self, q: Queries) -> np.ndarray:
        """queries x attributes: share of rows that meets each interval."""
        sound = q.low <= q.high
        return np.stack([np.where(sound[:, k], b[np.minimum(q.high[:, k] + 1, len(b) - 1)] - b[np.minimum(q.low[:, k], len(b) - 1)], 0) for k, b in enumerate(self.before)], axis=1)

    def estimate(self, q: Queries) -> np.ndarray:
        return self.shares_of(q).prod(axis=1) * self.rows

    def size_bytes(self) -> int:
        return 12 * self.numbers


class PairStatistics:
    """Column statistics with dependency degrees of all pairs and the common value pairs of the strongest ones.

    A query's attributes are taken up from the strongest dependency down: the
    dependent attribute's share p becomes d + (1 - d) p, d the degree. A query on
    exactly one stored pair of values takes that pair's own share.
    """

    def __init__(self, columns: ColumnStatistics, degree: np.ndarray, pairs: dict[tuple[int, int], dict[tuple[int, int], float]]) -> None:
        self.columns, self.degree, self.pairs = columns, degree, pairs

    @classmethod
    def fit(cls, tuples: DataFrame, dic: Dictionary, budget_bytes: int = 16_000) -> "PairStatistics":
        attrs = list(dic.attrs)
        sides = [(i, j) for i in range(len(attrs)) for j in range(len(attrs)) if i != j]
        cells = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(attrs[i]).alias("x"), F.col(attrs[j]).alias("y")) for i, j in sides))
        groups = tuples.select("mult", F.explode(cells).alias("c")).groupBy("c.i", "c.j", "c.x").agg(F.min("c.y").alias("low"), F.max("c.y").alias("high"), F.sum("mult").alias("n"))
        degree = np.zeros((len(attrs), len(attrs)))
        for r in groups.groupBy("i", "j").agg((F.sum(F.when(F.col("low") == F.col("high"), F.col("n")).otherwise(0)) / F.sum("n")).alias("d")).collect():  # one row a pair
            degree[r["i"], r["j"]] = r["d"]
        best = sorted({tuple(sorted(p)) for p in sides}, key=lambda p: (-max(degree[p], degree[p[::-1]]), p))[: max(1, len(attrs) // 2)]
        top = max(1, budget_bytes // 2 // (16 * len(best)))
        pairs = {}
        for i, j in best:
            rows = tuples.groupBy(attrs[i], attrs[j]).agg(F.sum("mult").alias("n")).orderBy(F.col("n").desc(), attrs[i], attrs[j]).limit(top).collect()  # the budget
            pairs[i, j] = {(r[0], r[1]): r["n"] / max(dic.rows, 1) for r in rows}
        return cls(ColumnStatistics.fit(dic, budget_bytes // 2), degree, pairs)

    def estimate(self, q: Queries) -> np.ndarray:
        p, bound = self.columns.shares_of(q), q.bound
        out = np.empty(len(q))
        order = sorted(((i, j) for i in range(p.shape[1]) for j in range(p.shape[1]) if i != j), key=lambda x: (-self.degree[x], x))
        for k in range(len(q)):
            asked = set(np.flatnonzero(bound[k]).tolist())
            pair = tuple(sorted(asked))
            if len(pair) == 2 and pair in self.pairs and (q.low[k] == q.high[k])[list(pair)].all():
                known = self.pairs[pair].get(tuple(int(q.low[k, a]) for a in pair))
                if known is not None:
                    out[k] = known
                    continue
            share, used = 1.0, set()
            for i, j in order:
                if i in asked and j in asked and j not in used and self.degree[i, j] > 0 and i not in used:
                    share *= self.degree[i, j] + (1 - self.degree[i, j]) * p[k, j]
                    used.add(j)
            out[k] = share * np.prod([p[k, a] for a in asked - used])
        return out * self.columns.rows

    def size_bytes(self) -> int:
        return self.columns.size_bytes() + 4 * self.degree.size + 16 * sum(map(len, self.pairs.values()))


class GridModel:
    """One grid over all attributes; each cell counts by the share of it that a query covers."""

    def __init__(self, counts: np.ndarray, bounds: list[list[tuple[int, int]]]) -> None:
        self.counts, self.bounds = counts, bounds

    @classmethod
    def fit(cls, tuples: DataFrame, dic: Dictionary, budget_bytes: int, kind: str = "width") -> "GridModel":
        grid, bounds = grid_histogram(tuples, dic, list(dic.attrs), budget_bytes, kind)
        counts = np.zeros([len(bounds[a]) for a in dic.attrs])
        for r in grid.collect():  # at most budget / 8 cells
            counts[tuple(r[f"b_{a}"] for a in dic.attrs)] = r["count"]
        return cls(counts, [bounds[a] for a in dic.attrs])

    def estimate(self, q: Queries) -> np.ndarray:
        out = np.empty(len(q))
        for lo in range(0, len(q), 256):
            rows, acc = slice(lo, lo + 256), None
            for k, bounds in enumerate(self.bounds):
                s, e = np.array(bounds).T
                f = np.maximum(0, np.minimum(q.high[rows, k][:, None], e) - np.maximum(q.low[rows, k][:, None], s) + 1) / (e - s + 1)
                acc = np.tensordot(f, self.counts, axes=(1, 0)) if acc is None else np.einsum("qb,qb...->q...", f, acc)
            out[rows] = acc
        return out

    def size_bytes(self) -> int:
        return 8 * self.counts.size


class WaveletModel:
    """Haar coefficients of the joint counts of a few attributes; the others count as independent."""

    def __init__(self, attrs: list[str], places: np.ndarray, values: np.ndarray, depths: list[int], columns: ColumnStatistics) -> None:
        self.attrs, self.places, self.values, self.depths, self.columns = attrs, places, values, depths, columns

    @classmethod
    def fit(cls, tuples: DataFrame, dic: Dictionary, attrs: list[str], budget_bytes: int) -> "WaveletModel":
        keep = max(1, budget_bytes // 2 // (8 + 4 * len(attrs)))
        rows = haar_top(haar_coefficients(tuples, dic, attrs), attrs, keep).collect()  # the budget
        depths = [max(0, math.ceil(math.log2(dic.cards[a]))) if dic.cards[a] > 1 else 0 for a in attrs]
        return cls(attrs, np.array([[r[f"c_{a}"] for a in attrs] for r in rows], np.int64).reshape(-1, len(attrs)), np.array([r["value"] for r in rows]), depths, ColumnStatistics.fit(dic, budget_bytes // 2))

    @staticmethod
    def _sums(c: np.ndarray, lo: np.ndarray, hi: np.ndarray, depth: int) -> np.ndarray:
        """queries x coefficients: sum of each basis function over each interval."""
        over = lambda s, e: np.maximum(0, np.minimum(hi[:, None], e) - np.maximum(lo[:, None], s) + 1)
        level = np.floor(np.log2(np.maximum(c, 1))).astype(int)
        width = 2 ** (depth - level)
        start = (c - 2**level) * width
        half = width // 2
        detail = (over(start, start + half - 1) - over(start + half, start + width - 1)) / np.sqrt(width)
        return np.where(c == 0, over(0 * c, 0 * c + 2**depth - 1) / math.sqrt(2**depth), detail)

    def estimate(self, q: Queries) -> np.ndarray:
        at = [q.attrs.index(a) for a in self.attrs]
        shares = self.columns.shares_of(q)
        rest = shares[:, [k for k in range(shares.shape[1]) if k not in at]].prod(axis=1)
        out = np.empty(len(q))
        for lo in range(0, len(q), 512):
            rows, value = slice(lo, lo + 512), self.values[None, :]
            for d, k in enumerate(at):
                value = value * self._sums(self.places[:, d], q.low[rows, k], q.high[rows, k], self.depths[d])
            out[rows] = np.maximum(0, value.sum(axis=1))
        return out * rest

    def size_bytes(self) -> int:
        return 8 * len(self.values) + 4 * self.places.size + self.columns.size_bytes()

