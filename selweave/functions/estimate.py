"""Estimates as a SQL function over condition texts."""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from selweave.operators.query import Queries, parse_where
from selweave.operators.ranges import box
from selweave.operators.relation import Dictionary


@dataclass
class Domains:
    """The values of a dictionary without its frame, so that tasks can bind conditions."""

    attrs: list[str]
    cards: dict[str, int]
    lists: dict[str, list]

    @classmethod
    def of(cls, dic: Dictionary) -> "Domains":
        return cls(list(dic.attrs), dic.cards, {a: dic.values(a) for a in dic.attrs})

    def values(self, attr: str) -> list:
        return self.lists[attr]

    code_range = Dictionary.code_range
    null_range = Dictionary.null_range


def selectivity_of(models: list[Any], dic: Dictionary, method: str = "auto", samples: int = 200):
    """Vectorised function: condition text -> estimated share of rows. A null text is null; an empty one asks for all rows."""
    domains = Domains.of(dic)

    @F.pandas_udf("double")
    def share(where: pd.Series) -> pd.Series:
        texts = where.dropna()
        q, of = Queries.of_predicates([parse_where(t) for t in texts], domains)
        found = [box(models, lo, hi, method, samples=samples, seed=0) for lo, hi in zip(q.low, q.high)]
        out = pd.Series(np.nan, index=where.index, dtype=object)
        out[texts.index] = np.minimum(1.0, np.bincount(of, found, len(texts)))
        return out.astype(float)

    return share


def register(spark: SparkSession, models: list[Any], dic: Dictionary, name: str = "est_selectivity", **options: Any) -> None:
    spark.udf.register(name, selectivity_of(models, dic, **options))
