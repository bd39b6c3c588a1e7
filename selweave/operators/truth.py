"""Exact answers of whole workloads in one scan.

Bitset strategy: for every attribute and code, a bit vector over the queries
says which of them the code doesn't rule out. A tuple's answers are the AND of
its codes' vectors; weighted column sums are the counts, popcounts the number of
queries a tuple satisfies. Counts are additive over partitions and increments.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .query import Queries

#: Bytes of bit vectors shipped to a task at most; larger workloads take several scans.
MASK_BYTES = 64 << 20


def masks(q: Queries) -> list[np.ndarray]:
    """One uint8 matrix an attribute: codes (and one for unknown values) x packed queries."""
    out = []
    for k, card in enumerate(q.cards):
        code = np.arange(card + 1)[:, None]
        hit = (code >= q.low[:, k]) & (code <= q.high[:, k])
        hit[card] = ~q.bound[:, k]  # an unseen value only passes where nothing is asked
        out.append(np.packbits(hit, axis=1))
    return out


def _answers(columns: list[np.ndarray], own: list[np.ndarray]) -> np.ndarray:
    acc = own[0][columns[0]]
    for codes, mask in zip(columns[1:], own[1:]):
        acc &= mask[codes]
    return acc


def _chunks(q: Queries) -> Iterator[Queries]:
    per = max(8, int(MASK_BYTES * 8 // max(1, sum(q.cards) + len(q.cards))))
    for lo in range(0, len(q), per):
        yield q.take(np.arange(lo, min(len(q), lo + per)))


def true_counts(codes: DataFrame, q: Queries) -> DataFrame:
    """(qid, true_rows) of every query over code tuples (with ``mult`` if compact)."""
    weighted = "mult" in codes.columns
    out = None
    for part in _chunks(q):
        own, n, ids = masks(part), len(part), part.qid.astype(np.int64)

        def run(batches: Iterator[pa.RecordBatch], own=own, n=n, ids=ids) -> Iterator[pa.RecordBatch]:
            total = np.zeros(n, np.int64)
            for batch in batches:
                columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(len(own))]
                mult = batch.column(len(own)).to_numpy(zero_copy_only=False) if weighted else None
                step = max(1, (8 << 20) // max(1, n))
                for lo in range(0, batch.num_rows, step):
                    bits = np.unpackbits(_answers([c[lo : lo + step] for c in columns], own), axis=1, count=n)
                    total += mult[lo : lo + step] @ bits if weighted else bits.sum(axis=0, dtype=np.int64)
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(total[at])], names=["qid", "c"])

        partial = codes.select(*q.attrs, *(["mult"] if weighted else [])).mapInArrow(run, "qid long, c long")
        out = partial if out is None else out.unionByName(partial)
    spark = codes.sparkSession
    asked = spark.createDataFrame([(int(x),) for x in q.qid], "qid long")
    if out is None:
        return asked.withColumn("true_rows", F.lit(0).cast("long"))
    summed = out.groupBy("qid").agg(F.sum("c").alias("true_rows"))
    return asked.join(summed, "qid", "left").select("qid", F.coalesce("true_rows", F.lit(0)).cast("long").alias("true_rows"))


def tuple_weights(codes: DataFrame, q: Queries, keep: list[str] | None = None) -> DataFrame:
    """Tuples with ``w``: how many queries each satisfies; no shuffle."""
    parts = [(masks(p), len(p)) for p in _chunks(q)]
    kept = [c for c in codes.columns if c not in q.attrs] if keep is None else keep
    rows = codes.select(*q.attrs, *kept)
    schema = rows.withColumn("w", F.lit(0).cast("long")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(len(q.attrs))]
            w = np.zeros(batch.num_rows, np.int64)
            for own, n in parts:
                step = max(1, (32 << 20) // max(1, n // 8 + 1))
                for lo in range(0, batch.num_rows, step):
                    acc = _answers([c[lo : lo + step] for c in columns], own)
                    if n % 8:
                        acc[:, -1] &= 256 - (1 << (8 - n % 8))
                    w[lo : lo + step] += np.bitwise_count(acc).sum(axis=1, dtype=np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(w)], names=[*batch.schema.names, "w"])

    return rows.mapInArrow(run, schema)


def true_counts_grouped(codes: DataFrame, preds: DataFrame, attrs: list[str]) -> DataFrame:
    """Point queries by equi-join: counts of the asked attribute sets, joined on the cell's text."""
    asked = preds.groupBy("qid").agg(F.concat_ws(",", F.sort_array(F.collect_list("attr"))).alias("attrs"), F.concat_ws(",", F.transform(F.sort_array(F.collect_list(F.struct("attr", "lo"))), lambda x: x["lo"].cast("string"))).alias("cell"))
    sets = [r["attrs"] for r in asked.select("attrs").distinct().collect()]  # at most one row an attribute set
    weighted = F.col("mult") if "mult" in codes.columns else F.lit(1)
    named = F.array(*(F.struct(F.lit(s).alias("attrs"), F.concat_ws(",", *(F.col(a).cast("string") for a in s.split(","))).alias("cell")) for s in sets))
    counts = codes.select(weighted.alias("m"), F.explode(named).alias("x")).groupBy("x.attrs", "x.cell").agg(F.sum("m").alias("c"))
    return asked.join(counts, ["attrs", "cell"], "left").select("qid", F.coalesce("c", F.lit(0)).cast("long").alias("true_rows"))


def true_counts_theta(codes: DataFrame, q: Queries) -> DataFrame:
    """By inequality join of tuples and queries; for tests and small workloads only."""
    frame = F.broadcast(q.frame(codes.sparkSession))  # bounded: a workload
    inside = None
    for k, a in enumerate(q.attrs):
        one = F.col(a).between(F.col("low")[k], F.col("high")[k])
        inside = one if inside is None else inside & one
    weighted = F.col("mult") if "mult" in codes.columns else F.lit(1)
    return frame.join(codes, inside, "left").groupBy("qid").agg(F.coalesce(F.sum(F.when(F.col(q.attrs[0]).isNotNull(), weighted)), F.lit(0)).cast("long").alias("true_rows"))
