"""Kernel density over codes: every sampled row spreads its mass around its place in each domain."""

from __future__ import annotations

from collections.abc import Iterator
from math import erf, sqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from .baselines import md5_sample
from .query import Queries
from .relation import Dictionary

_cdf = np.vectorize(lambda x: 0.5 * (1 + erf(x / sqrt(2))), otypes=[float])


class KernelDensity:
    """Product of Gaussian kernels cut off at the ends of each domain; a code covers half a unit on both sides.

    The sample holds about ``most`` rows (documented bound of what travels to tasks).
    """

    def __init__(self, codes: np.ndarray, weight: np.ndarray, cards: list[int], scale: float = 1.0) -> None:
        self.codes, self.cards = codes, list(cards)
        self.weight = weight / max(weight.sum(), 1e-300)
        mean = self.weight @ codes
        spread = np.sqrt(np.maximum(self.weight @ (codes - mean) ** 2, 0))
        self.width = np.maximum(scale * spread * max(weight.sum(), 1.0) ** (-1 / (4 + codes.shape[1])), 1e-3)

    @classmethod
    def fit(cls, tuples: DataFrame, dic: Dictionary, most: int = 2_000, scale: float = 0.3, seed: int = 42) -> "KernelDensity":
        attrs = list(dic.attrs)
        rows = md5_sample(tuples, attrs, min(1.0, most / max(dic.rows, 1)), seed).toPandas()
        return cls(rows[attrs].to_numpy(float).reshape(len(rows), len(attrs)), rows["mult"].to_numpy(float), [dic.cards[a] for a in attrs], scale)

    def selectivity(self, low: np.ndarray, high: np.ndarray) -> float:
        """Mass of a box of codes; 0 if an interval is empty."""
        if (low > high).any() or not len(self.codes):
            return 0.0
        out = self.weight.copy()
        for a, card in enumerate(self.cards):
            if low[a] <= 0 and high[a] >= card - 1:
                continue
            at, back = np.unique(self.codes[:, a], return_inverse=True)
            h = self.width[a]
            whole = _cdf((card - 0.5 - at) / h) - _cdf((-0.5 - at) / h)
            own = (_cdf((high[a] + 0.5 - at) / h) - _cdf((low[a] - 0.5 - at) / h)) / np.maximum(whole, 1e-300)
            out *= own[back.ravel()]
        return float(out.sum())

    def size_bytes(self) -> int:
        return self.codes.shape[0] * (4 * self.codes.shape[1] + 8)


def estimate(spark: SparkSession, model: KernelDensity, q: Queries, rows: int, tasks: int = 16) -> DataFrame:
    """(qid, est_rows), queries spread over tasks."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            found = [model.selectivity(np.array(lo), np.array(hi)) for lo, hi in zip(part["low"], part["high"])]
            yield pd.DataFrame({"qid": part["qid"], "est_rows": np.array(found, float) * rows})

    return q.frame(spark).repartition(tasks, "qid").mapInPandas(run, "qid long, est_rows double")
