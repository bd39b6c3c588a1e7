"""What the registered queries share: relations with their dictionaries, logs, errors and boxes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from selweave.functions.metrics import box_plot, q_error, selectivity_bucket
from selweave.operators import workload as wl
from selweave.operators.query import Queries
from selweave.operators.relation import Dictionary, compact, encode_codes, entropies, fit_dictionary
from selweave.operators.truth import true_counts
from selweave.sources.views import VIEWS, load_view

Query = Callable[[SparkSession, str], DataFrame]
TOTAL = 10_000  # queries of a combination workload
BOX = ("p05", "p25", "p50", "p75", "p95", "mean", "max")


@dataclass
class Relation:
    name: str
    attrs: list[str]
    dic: Dictionary
    tuples: DataFrame


def relation(spark: SparkSession, sf_dir: str, name: str, attrs: list[str] | None = None) -> Relation:
    attrs = attrs or list(VIEWS[name].attributes)
    df = load_view(spark, sf_dir, name)
    dic = fit_dictionary(df, attrs)
    dic.frame = dic.frame.persist()
    return Relation(name, attrs, dic, compact(encode_codes(df, dic), attrs).persist())


def combo(spark: SparkSession, r: Relation, total: int = TOTAL, seed: int = 42, values: str = "uniform") -> DataFrame:
    return wl.combo_workload(spark, r.dic, total, seed, values, r.tuples).persist()


def rounded(df: DataFrame, *names: str, digits: int = 4) -> DataFrame:
    """Rounded columns; lifted a little first, so that ties fall alike in any engine."""
    return df.select(*((F.round(F.col(c) * F.lit(1.000000001), digits) + F.lit(0.0)).alias(c) if c in names else F.col(c) for c in df.columns))


def errors(truth: DataFrame, est: DataFrame) -> DataFrame:
    return truth.join(est, "qid").withColumn("qerr", q_error(F.col("true_rows"), F.col("est_rows")))


def box(found: DataFrame, *by: str) -> DataFrame:
    return rounded(box_plot(found, list(by)), *BOX)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def labelled(r: Relation, preds: DataFrame) -> tuple[Queries, np.ndarray]:
    """A training log with its answers."""
    q = Queries.of_frame(preds, r.dic)
    got = {x["qid"]: x["true_rows"] for x in true_counts(r.tuples, q).collect()}  # bounded: a training log
    return q, np.array([got[int(i)] for i in q.qid], float)


def grouped(r: Relation, found: DataFrame, w: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """Rows (qid, true_rows) with the columns that results are grouped by: k, bucket, decade, quartile."""
    found = found.join(w.select("qid", F.col("k").cast("int").alias("k"), "attrs").distinct(), "qid")
    if "bucket" in by:
        found = found.withColumn("bucket", selectivity_bucket(F.col("true_rows") / F.lit(float(r.dic.rows))))
    if "decade" in by:
        size = F.lit(0.0)
        for a in r.attrs:
            size = size + F.when(F.array_contains(F.split("attrs", ","), a), F.lit(float(np.log10(r.dic.cards[a])))).otherwise(0.0)
        found = found.withColumn("decade", F.floor(size + 1e-9).cast("int"))
    if "quartile" in by:
        sets = [tuple(s.split(",")) for _, s, quota in wl.attribute_sets(r.attrs, TOTAL) if quota]
        h = entropies(r.tuples, sets).select("attrs", F.round("entropy", 6).alias("h"))
        found = found.join(F.broadcast(h.select("attrs", F.ntile(4).over(Window.orderBy("h", "attrs")).alias("quartile"))), "attrs")  # one row an attribute set
    return found
