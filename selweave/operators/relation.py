"""Relations as codes: dictionaries, encoding, and distinct tuples with multiplicity."""

from __future__ import annotations

import math
from bisect import bisect_left, bisect_right
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

#: Dictionaries of up to so many values are broadcast; larger ones are joined by shuffle.
BROADCAST_VALUES = 200_000
#: Dictionaries of up to so many values may come to the driver.
DRIVER_VALUES = 2_000_000


def _number(df: DataFrame, attr: str) -> bool:
    return isinstance(df.schema[attr].dataType, T.NumericType)


def fit_dictionary(df: DataFrame, attrs: list[str]) -> "Dictionary":
    """Order-preserving codes of all attributes from one scan; a null is the lowest code of its attribute.

    Every row gives one entry an attribute, summed map-side before the shuffle.
    """
    entries = F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value"), (F.col(a).cast("double") if _number(df, a) else F.lit(None).cast("double")).alias("sort")) for a in attrs))
    counted = df.select(F.explode(entries).alias("e")).groupBy("e.attr", "e.value", "e.sort").agg(F.count("*").alias("freq"))
    order = Window.partitionBy("attr").orderBy(F.col("sort").asc_nulls_first(), F.col("value").asc_nulls_first())
    frame = counted.withColumn("code", (F.row_number().over(order) - 1).cast("int")).select("attr", "code", "value", "sort", "freq")
    return Dictionary(frame, list(attrs), {a: _number(df, a) for a in attrs})


@dataclass
class Dictionary:
    """(attr, code, value, sort, freq), distributed; small parts come to the driver on demand."""

    frame: DataFrame
    attrs: list[str]
    numeric: dict[str, bool]
    _values: dict[str, list] = field(default_factory=dict, repr=False)

    @cached_property
    def cards(self) -> dict[str, int]:
        found = {r["attr"]: r["n"] for r in self.frame.groupBy("attr").agg(F.count("*").alias("n")).collect()}
        return {a: int(found.get(a, 0)) for a in self.attrs}

    @cached_property
    def rows(self) -> int:
        return int(self.frame.where(F.col("attr") == self.attrs[0]).agg(F.coalesce(F.sum("freq"), F.lit(0))).first()[0])

    def values(self, attr: str) -> list[tuple[object, int]]:
        """(value, frequency) by code; numbers for numeric attributes, None for a null."""
        if attr not in self._values:
            if self.cards[attr] > DRIVER_VALUES:
                raise ValueError(f"{attr} has too many values for the driver; join with the frame instead")
            rows = self.frame.where(F.col("attr") == attr).orderBy("code").select("value", "sort", "freq").collect()
            self._values[attr] = [((r["sort"] if self.numeric[attr] and r["value"] is not None else r["value"]), r["freq"]) for r in rows]
        return self._values[attr]

    def code_range(self, attr: str, low: object = None, high: object = None, low_open: bool = False, high_open: bool = False) -> tuple[int, int]:
        """Codes of the values between two bounds (None: open end); empty as (1, 0). Nulls never match."""
        values = [v for v, _ in self.values(attr)]
        first = 1 if values and values[0] is None else 0
        keys = values[first:]
        lo = 0 if low is None else (bisect_right if low_open else bisect_left)(keys, low)
        hi = len(keys) if high is None else (bisect_left if high_open else bisect_right)(keys, high)
        return (first + lo, first + hi - 1) if lo < hi else (1, 0)

    def null_range(self, attr: str) -> tuple[int, int]:
        values = self.values(attr)
        return (0, 0) if values and values[0][0] is None else (1, 0)

    def bits(self) -> dict[str, int]:
        return {a: max(0, math.ceil(math.log2(max(1, c)))) for a, c in self.cards.items()}

    def joint_size(self) -> int:
        return math.prod(self.cards.values())

    def independent_size(self) -> int:
        return sum(self.cards.values())


def encode_codes(df: DataFrame, dic: Dictionary, keep: list[str] | None = None) -> DataFrame:
    """Attributes replaced by codes; a value not in the dictionary gets the code after the last."""
    out = df.select(*dic.attrs, *(keep or []))
    for a in dic.attrs:
        own = dic.frame.where(F.col("attr") == a).select(F.col("value").alias(f"_{a}"), F.col("code").alias(f"_code_{a}"))
        if dic.cards[a] <= BROADCAST_VALUES:
            own = F.broadcast(own)
        out = out.join(own, F.col(a).cast("string").eqNullSafe(F.col(f"_{a}")), "left").withColumn(a, F.coalesce(f"_code_{a}", F.lit(dic.cards[a])).cast("int")).drop(f"_{a}", f"_code_{a}")
    return out.select(*dic.attrs, *(keep or []))


def compact(codes: DataFrame, attrs: list[str]) -> DataFrame:
    """Distinct tuples with their number: equal tuples share one term of any loss or count."""
    if "mult" in codes.columns:
        return codes.groupBy(*attrs).agg(F.sum("mult").alias("mult"))
    return codes.groupBy(*attrs).agg(F.count("*").alias("mult"))


# --- encodings of tuples ---


def binary_bits(dic: Dictionary) -> Column:
    """Array of 0/1: each code by its bits, most significant first; one-value domains take none."""
    parts = [F.array(*(F.shiftright(F.col(a), i).bitwiseAND(F.lit(1)) for i in range(b - 1, -1, -1))) for a, b in dic.bits().items() if b > 0]
    return F.flatten(F.array(*parts)) if parts else F.array().cast("array<int>")


def one_hot(dic: Dictionary) -> Column:
    """Array of 0/1 with one slot a value."""
    return F.flatten(F.array(*(F.expr(f"transform(sequence(0, {c - 1}), i -> int(`{a}` = i))") for a, c in dic.cards.items() if c > 0)))


def encoding_width(dic: Dictionary, kind: str = "binary") -> int:
    return sum(dic.bits().values()) if kind == "binary" else sum(dic.cards.values())


def bit_matrix(codes: np.ndarray, bits: list[int]) -> np.ndarray:
    """uint8 matrix of the binary encoding of code rows."""
    parts = [(codes[:, [k]] >> np.arange(b - 1, -1, -1)) & 1 for k, b in enumerate(bits) if b]
    return np.concatenate(parts, axis=1).astype(np.uint8) if parts else np.zeros((len(codes), 0), np.uint8)


def one_hot_matrix(codes: np.ndarray, cards: list[int]) -> np.ndarray:
    return np.concatenate([codes[:, [k]] == np.arange(c) for k, c in enumerate(cards)], axis=1).astype(np.uint8)


# --- information measures ---


def joint_entropy(tuples: DataFrame, attrs: list[str]) -> float:
    """Bits of the joint distribution of some attributes of compact tuples."""
    counts = tuples.groupBy(*attrs).agg(F.sum("mult").alias("_c"))
    r = counts.agg(F.sum("_c").alias("n"), F.sum(F.col("_c") * F.log2("_c")).alias("s")).first()
    return math.log2(r["n"]) - r["s"] / r["n"] if r["n"] else 0.0


def entropies(tuples: DataFrame, sets: list[tuple[str, ...]]) -> DataFrame:
    """(attrs, n_groups, entropy) of many attribute sets in one pass over the compact tuples."""
    attrs = sorted({a for s in sets for a in s})
    bit = {a: 1 << k for k, a in enumerate(attrs)}
    names = [(",".join(s), sum(bit[a] for a in set(s))) for s in sets]
    asked = tuples.sparkSession.createDataFrame(names, "attrs string, _set long")
    each = tuples.select("mult", *attrs, F.explode(F.array(*(F.lit(m).cast("long") for m in sorted({m for _, m in names})))).alias("_set"))
    # an attribute outside the set counts as one value, so one expression an attribute serves all sets
    counts = each.groupBy("_set", *(F.when(F.col("_set").bitwiseAND(F.lit(bit[a]).cast("long")) != 0, F.col(a)).alias(f"_at_{a}") for a in attrs)).agg(F.sum("mult").alias("_c"))
    sums = counts.groupBy("_set").agg(F.count("*").alias("n_groups"), F.sum("_c").alias("n"), F.sum(F.col("_c") * F.log2("_c")).alias("s")).join(F.broadcast(asked), "_set")
    return sums.select("attrs", "n_groups", (F.log2("n") - F.col("s") / F.col("n")).alias("entropy"))


def mutual_information(tuples: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """(a, b, mi) in bits for pairs of attributes."""
    singles = sorted({x for p in pairs for x in p})
    found = entropies(tuples, [(s,) for s in singles] + [tuple(p) for p in pairs])
    asked = tuples.sparkSession.createDataFrame([(a, b, f"{a},{b}") for a, b in pairs], "a string, b string, ab string")
    e = lambda name: F.broadcast(found.select(F.col("attrs").alias(name), F.col("entropy").alias(f"h_{name}")))  # noqa: E731  one row a set
    return asked.join(e("a"), "a").join(e("b"), "b").join(e("ab"), "ab").select("a", "b", F.greatest(F.lit(0.0), F.col("h_a") + F.col("h_b") - F.col("h_ab")).alias("mi"))


def dependencies(tuples: DataFrame, attrs: list[str]) -> DataFrame:
    """(determinant, dependent): pairs where each value of the first goes with one value of the second."""
    pairs = [(a, b) for a in attrs for b in attrs if a != b]
    both = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(a).alias("x"), F.col(b).alias("y")) for a, b in pairs))
    groups = tuples.select(F.explode(both).alias("p")).groupBy("p.a", "p.b", "p.x").agg(F.min("p.y").alias("low"), F.max("p.y").alias("high"))
    held = groups.groupBy("a", "b").agg(F.max((F.col("low") != F.col("high")).cast("int")).alias("broken"))
    return held.where("broken = 0").select(F.col("a").alias("determinant"), F.col("b").alias("dependent"))


def discretise(df: DataFrame, column: str, bins: int, kind: str = "quantile") -> Column:
    """Bin number of a numeric column: equal width, or equal depth by exact quantiles."""
    if kind == "width":
        low, high = df.agg(F.min(column), F.max(column)).first()
        width = (high - low) / bins or 1.0
        return F.least(F.floor((F.col(column) - low) / width), F.lit(bins - 1)).cast("int")
    cuts = df.agg(F.percentile(column, F.array(*(F.lit(k / bins) for k in range(1, bins))))).first()[0]
    return sum((F.col(column) > F.lit(c)).cast("int") for c in sorted(set(cuts)))
