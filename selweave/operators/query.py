"""Conjunctive queries: builders, a small parser of conditions, and binding to codes."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .relation import Dictionary


@dataclass(frozen=True)
class Predicate:
    attr: str
    op: str  # = < <= > >= between in null
    args: tuple = ()


def eq(attr: str, value: object) -> Predicate:
    return Predicate(attr, "=", (value,))


def between(attr: str, low: object, high: object) -> Predicate:
    return Predicate(attr, "between", (low, high))


def lt(attr: str, value: object) -> Predicate:
    return Predicate(attr, "<", (value,))


def le(attr: str, value: object) -> Predicate:
    return Predicate(attr, "<=", (value,))


def gt(attr: str, value: object) -> Predicate:
    return Predicate(attr, ">", (value,))


def ge(attr: str, value: object) -> Predicate:
    return Predicate(attr, ">=", (value,))


def isin(attr: str, *values: object) -> Predicate:
    return Predicate(attr, "in", values)


def is_null(attr: str) -> Predicate:
    return Predicate(attr, "null")


_TOKEN = re.compile(r"\s*(?:(?P<str>'(?:[^']|'')*')|(?P<num>-?\d+(?:\.\d+)?)|(?P<op><=|>=|=|<|>)|(?P<name>[A-Za-z_]\w*)|(?P<p>[(),]))")


def parse_where(text: str) -> list[Predicate]:
    """Conditions joined by AND: comparisons, BETWEEN, IN, IS NULL."""
    tokens, at = [], 0
    text = text.strip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"can't read {text[at:]!r}")
        at = m.end()
        kind = m.lastgroup
        value: object = m[kind]
        if kind == "str":
            value = value[1:-1].replace("''", "'")
        elif kind == "num":
            value = float(value) if "." in value else int(value)
        elif kind == "name" and value.upper() in ("AND", "BETWEEN", "IN", "IS", "NULL"):
            kind, value = "word", value.upper()
        tokens.append((kind, value))
    out, k = [], 0

    def take(*kinds: str) -> object:
        nonlocal k
        if k >= len(tokens) or tokens[k][0] not in kinds:
            raise ValueError(f"expected {' or '.join(kinds)} in {text!r}")
        k += 1
        return tokens[k - 1][1]

    while k < len(tokens):
        if out and take("word") != "AND":
            raise ValueError("conditions are joined by AND")
        attr = take("name")
        found = take("op", "word")
        if found == "BETWEEN":
            low = take("str", "num")
            take("word")
            out.append(between(attr, low, take("str", "num")))
        elif found == "IN":
            take("p")
            values = [take("str", "num")]
            while take("p") == ",":
                values.append(take("str", "num"))
            out.append(isin(attr, *values))
        elif found == "IS":
            take("word")
            out.append(is_null(attr))
        else:
            out.append(Predicate(attr, found, (take("str", "num"),)))
    return out


def code_sets(predicates: list[Predicate], dic: Dictionary) -> dict[str, list[tuple[int, int]]]:
    """Attribute -> disjoint code intervals; conditions on one attribute are intersected; none left is []."""
    out: dict[str, list[tuple[int, int]]] = {}
    for p in predicates:
        if p.op == "=":
            found = [dic.code_range(p.attr, p.args[0], p.args[0])]
        elif p.op == "between":
            found = [dic.code_range(p.attr, *p.args)]
        elif p.op in ("<", "<="):
            found = [dic.code_range(p.attr, None, p.args[0], high_open=p.op == "<")]
        elif p.op in (">", ">="):
            found = [dic.code_range(p.attr, p.args[0], None, low_open=p.op == ">")]
        elif p.op == "in":
            found = sorted({dic.code_range(p.attr, v, v) for v in p.args})
        else:
            found = [dic.null_range(p.attr)]
        found = [x for x in found if x[0] <= x[1]]
        if p.attr in out:
            found = [(max(a, c), min(b, d)) for a, b in out[p.attr] for c, d in found if max(a, c) <= min(b, d)]
        out[p.attr] = found
    return out


@dataclass
class Queries:
    """Bound queries: one row and one closed code interval an attribute; a full interval is no condition."""

    attrs: list[str]
    cards: list[int]
    qid: np.ndarray
    low: np.ndarray  # queries x attributes
    high: np.ndarray

    def __len__(self) -> int:
        return len(self.qid)

    @property
    def bound(self) -> np.ndarray:
        return (self.low > 0) | (self.high < np.array(self.cards) - 1)

    def take(self, rows: np.ndarray) -> "Queries":
        return Queries(self.attrs, self.cards, self.qid[rows], self.low[rows], self.high[rows])

    def frame(self, spark: SparkSession) -> DataFrame:
        """(qid, low, high) with arrays in attribute order."""
        rows = [(int(q), lo, hi) for q, lo, hi in zip(self.qid, self.low.tolist(), self.high.tolist())]
        return spark.createDataFrame(rows, "qid long, low array<int>, high array<int>")

    @classmethod
    def of_frame(cls, preds: DataFrame, dic: Dictionary, ids: DataFrame | None = None) -> "Queries":
        """From long rows (qid, attr, lo, hi) of a workload; conditions on one attribute are intersected."""
        rows = preds.select("qid", "attr", "lo", "hi").toPandas()
        qid = np.unique(rows["qid"].to_numpy()) if ids is None else np.sort(ids.select("qid").toPandas()["qid"].to_numpy())
        cards = [dic.cards[a] for a in dic.attrs]
        low, high = np.zeros((len(qid), len(cards)), np.int32), np.tile(np.array(cards, np.int32) - 1, (len(qid), 1))
        q, a = np.searchsorted(qid, rows["qid"].to_numpy()), rows["attr"].map({x: k for k, x in enumerate(dic.attrs)}).to_numpy()
        np.maximum.at(low, (q, a), rows["lo"].to_numpy(np.int32))
        np.minimum.at(high, (q, a), rows["hi"].to_numpy(np.int32))
        return cls(list(dic.attrs), cards, qid, low, high)

    @classmethod
    def of_predicates(cls, asked: list[list[Predicate]], dic: Dictionary) -> tuple["Queries", np.ndarray]:
        """Boxes of queries that may hold IN lists: (boxes, query of each box). Boxes of a query are disjoint."""
        cards = [dic.cards[a] for a in dic.attrs]
        low, high, of = [], [], []
        for k, predicates in enumerate(asked):
            boxes = [([0] * len(cards), [c - 1 for c in cards])]
            for attr, ranges in code_sets(predicates, dic).items():
                at = dic.attrs.index(attr)
                boxes = [(lo[:at] + [a] + lo[at + 1 :], hi[:at] + [b] + hi[at + 1 :]) for lo, hi in boxes for a, b in ranges]
            for lo, hi in boxes:
                low.append(lo)
                high.append(hi)
                of.append(k)
        shape = (len(low), len(cards))
        return cls(list(dic.attrs), cards, np.arange(len(low)), np.array(low, np.int32).reshape(shape), np.array(high, np.int32).reshape(shape)), np.array(of, np.int64)


def canonical(preds: DataFrame) -> DataFrame:
    """(qid, k, canon): sorted conditions as text, the identity of a query."""
    return preds.groupBy("qid").agg(F.count("*").cast("int").alias("k"), F.concat_ws(",", F.sort_array(F.collect_list(F.concat(F.col("attr"), F.lit("="), F.col("lo").cast("string"), F.lit(".."), F.col("hi").cast("string"))))).alias("canon"))
