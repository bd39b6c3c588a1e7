"""Query logs in and out, and a store of trained models."""

from __future__ import annotations

import pickle
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from selweave.operators.query import Queries, parse_where
from selweave.operators.relation import Dictionary


def read_log(spark: SparkSession, path: str, kind: str = "text") -> DataFrame:
    """(qid, where) of a log: a condition a line (text), or records with qid and where (json, csv, parquet). Empty lines are no queries.

    The qid of a line is a hash of its text, so equal lines are one query and a
    log may be read in parts.
    """
    if kind == "text":
        lines = spark.read.text(path).select(F.trim("value").alias("where")).where("where <> ''")
        return lines.distinct().select(F.xxhash64("where").alias("qid"), "where")
    options = {"header": "true"} if kind == "csv" else {}
    return spark.read.schema("qid long, where string").options(**options).format(kind).load(path)


def bind_log(log: DataFrame, dic: Dictionary) -> tuple[Queries, list[int]]:
    """(boxes, qid of each box); the log is a workload that fits the driver."""
    rows = log.orderBy("qid").collect()
    boxes, of = Queries.of_predicates([parse_where(r["where"]) for r in rows], dic)
    return boxes, [rows[k]["qid"] for k in of.tolist()]


def write_labelled(labelled: DataFrame, path: str) -> None:
    """Labelled queries as Parquet, one folder a predicate count ``k``."""
    labelled.write.mode("overwrite").partitionBy("k").parquet(path)


def save_models(spark: SparkSession, models: list[Any], path: str, name: str, version: int) -> None:
    """Adds a version of a named model; one row a network."""
    rows = [(name, version, k, m.size_bytes(), bytearray(pickle.dumps(m))) for k, m in enumerate(models)]
    spark.createDataFrame(rows, "name string, version int, part int, bytes long, model binary").write.mode("append").partitionBy("name").parquet(path)


def load_models(spark: SparkSession, path: str, name: str, version: int | None = None) -> list[Any]:
    """The networks of a version (the latest). Models are pickled: read only stores you wrote."""
    own = spark.read.parquet(path).where(F.col("name") == name)
    if version is None:
        version = own.agg(F.max("version")).first()[0]
    return [pickle.loads(r["model"]) for r in own.where(F.col("version") == version).orderBy("part").select("model").collect()]
