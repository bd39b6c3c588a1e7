"""What a planner does with estimates: join strategy, partition count, order of conditions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from selweave.operators.relation import Dictionary


def join_advice(estimates: DataFrame, row_bytes: int, broadcast_bytes: int = 10 << 20, partition_bytes: int = 128 << 20) -> DataFrame:
    """(qid, strategy, partitions) for relations of ``est_rows`` rows of ``row_bytes`` each."""
    size = F.col("est_rows") * F.lit(float(row_bytes))
    return estimates.select("qid", F.when(size <= broadcast_bytes, "broadcast").otherwise("shuffle").alias("strategy"), F.greatest(F.lit(1), F.ceil(size / F.lit(float(partition_bytes)))).cast("int").alias("partitions"))


def hinted(frame: DataFrame, strategy: str) -> DataFrame:
    """The frame with the hint the advice asks for."""
    return F.broadcast(frame) if strategy == "broadcast" else frame.hint("merge")


def condition_order(preds: DataFrame, dic: Dictionary) -> DataFrame:
    """(qid, attr, place): the most selective condition of each query first.

    Equality conditions on codes; an unseen code has frequency 0.
    """
    freq = dic.frame.select("attr", F.col("code").alias("lo"), "freq")
    known = preds.join(freq, ["attr", "lo"], "left").withColumn("freq", F.coalesce("freq", F.lit(0)))
    return known.select("qid", "attr", F.row_number().over(Window.partitionBy("qid").orderBy("freq", "attr")).alias("place"))
