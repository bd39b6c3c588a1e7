"""Increments as streams: windowed counts, and network updates by micro-batch."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from selweave.operators import dens
from selweave.operators.relation import Dictionary, compact, encode_codes
from selweave.sources.views import table


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(table(spark, sf_dir, "events").schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def hourly(stream: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Counts and sums of one-hour windows; rows later than the watermark are dropped."""
    windows = stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness).groupBy(F.window("ts", "1 hour").alias("w"), "event_type")
    return windows.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").cast("timestamp_ntz").alias("hour"), "event_type", "n", F.round("total", 2).alias("total"))


def hourly_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All that the stream holds now, in complete mode; the result stays in memory (windows x event types)."""
    name = f"hourly_{uuid.uuid4().hex}"
    hourly(events_stream(spark, sf_dir)).writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def updating(stream: DataFrame, dic: Dictionary, models: list[dens.MaskedNet], publish: Callable[[list[dens.MaskedNet], int], None], epochs: int = 5, dropout: float = 0.1):
    """A stream writer that fine-tunes the networks on each micro-batch; ``publish`` gets each new set.

    The caller sets checkpoint location and trigger. A replayed batch tunes from the last published set.
    """
    held = {"models": models}

    def each(batch: DataFrame, number: int) -> None:
        held["models"] = dens.fine_tune(held["models"], compact(encode_codes(batch, dic), dic.attrs), dic, epochs, dropout)
        publish(held["models"], number)

    return stream.writeStream.foreachBatch(each)
