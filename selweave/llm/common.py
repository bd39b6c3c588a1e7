"""Vectorised text primitives shared by the training-data operators.

Everything works on the raw UTF-8 buffer of an Arrow string column, so a batch
of documents is tokenised by a handful of numpy passes and not word by word.
"""

from __future__ import annotations

import gc
import re
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The bytes that separate words (space, tab, LF, VT, FF, CR).
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)

WORD_RE = r"[^\x20\x09-\x0D]+"
_STEP = np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x100000001B3F1D55 | 1
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]

IS_SPACE = np.zeros(256, bool)
IS_SPACE[list(SPACES)] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share. Without one, a session on one machine takes a folder of its own; a cluster must name it."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        at = tempfile.mkdtemp(prefix="checkpoints-")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(at)
    return at


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder, which ends the lineage.

    First the driver's garbage goes: Spark's cleaner deletes shuffle files and
    checkpoints once nothing on the driver refers to them, and what earlier cuts
    were made from is no longer needed.
    """
    shared_folder(df.sparkSession)
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return df.checkpoint(eager=True)


def skew_join(left: DataFrame, right: DataFrame, keys: list[str], weight: str, spread: Column, share: int = 1000) -> DataFrame:
    """Left join with a table of one row a key, where few keys may hold most rows of ``left``.

    ``weight`` is a column of ``right``: how many rows of ``left`` a key has, or
    in proportion to it. Keys above one ``share``th of all weight, which are
    fewer than ``share`` by that, are joined by broadcast and stay where they
    are; the others are shuffled, and ``spread`` (a column of ``left``) deals the
    former so that no task gets all of a key.
    """
    total = right.agg(F.sum(weight)).first()[0] or 0
    heavy = F.col(weight) > F.lit(total / share)
    extra = [c for c in right.columns if c not in keys]
    hot = right.where(heavy).select(*(F.col(k).alias(f"_hot_{k}") for k in keys), F.struct(*extra).alias("_hot"))
    met = None
    for k in keys:
        one = F.col(k) == F.col(f"_hot_{k}")
        met = one if met is None else met & one
    first, rest = keys[0], keys[1:]
    marked = left.join(F.broadcast(hot), met, "left").drop(*(f"_hot_{k}" for k in keys))
    marked = marked.withColumn("_cold", F.col("_hot").isNull()).withColumn("_first", F.when(F.col("_cold"), F.col(first)).otherwise(F.xxhash64(spread)))
    cold = right.where(~heavy).withColumn("_cold", F.lit(True)).withColumn("_first", F.col(first)).drop(first)
    cold = cold.select(*rest, "_cold", "_first", *(F.col(c).alias(f"_own_{c}") for c in extra))
    joined = marked.join(cold, ["_first", "_cold", *rest], "left")
    return joined.select(*left.columns, *(F.coalesce(F.col(f"_hot.{c}"), F.col(f"_own_{c}")).alias(c) for c in extra))


def slices(batches: Iterable[pa.RecordBatch], column: str, max_bytes: int = 1 << 20, max_rows: int = 4096) -> Iterator[pa.RecordBatch]:
    """Cut batches so that no piece holds over ``max_bytes`` of ``column`` unless a single row does."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        offsets = text_buffer(batch.column(batch.schema.get_field_index(column)))[1]
        lo = 0
        while lo < n:
            hi = int(np.searchsorted(offsets, offsets[lo] + max_bytes, "right")) - 1
            hi = min(max(hi, lo + 1), lo + max_rows, n)
            yield batch.slice(lo, hi - lo)
            lo = hi


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null is an empty text. Offsets start at 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, offsets - offsets[0]


def edges(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of true bytes; a run never crosses a document."""
    n = len(inside)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    at = offsets[1:-1]
    at = at[at < n]
    first[at] = inside[at]
    last = inside.copy()
    last[:-1] &= first[1:] | ~inside[1:]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def owner(starts: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """The document of each position."""
    return np.searchsorted(offsets, starts, "right") - 1


def first_of_each(starts: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """For positions in order: index of the first at or after each document's start (length documents + 1)."""
    return np.searchsorted(starts, offsets, "left")


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) <= n:
        size = max(n + 1, 1 << 16)
        inverse = pow(_BASE, -1, 1 << 64)
        for k, base in enumerate((_BASE, inverse)):
            powers = np.full(size, base, np.uint64)
            powers[0] = 1
            _POWERS[k] = np.cumprod(powers, dtype=np.uint64)
    return _POWERS[0], _POWERS[1]


def prefix_hashes(raw: np.ndarray) -> np.ndarray:
    """Prefix sums of byte * base**position, modulo 2**64 (length n + 1)."""
    up, _ = _powers(len(raw))
    sums = np.empty(len(raw) + 1, np.uint64)
    sums[0] = 0
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=sums[1:])
    return sums


def span_hashes(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each span, independent of where it stands."""
    _, down = _powers(len(sums))
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def mix(h: np.ndarray) -> np.ndarray:
    """Spread all input bits over the 64 output bits."""
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= _STEP
    return h ^ (h >> np.uint64(32))


def held_out(doc_id, modulus: int, remainder: int):
    """Column: crc32 of the id as text leaves this remainder. A null id counts as the empty text."""
    return (F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % modulus) == remainder


def small_batches(df: DataFrame, size: int = 4 << 20) -> DataFrame:
    """The same rows; has the session hand texts to Python in Arrow batches of at most ``size`` bytes."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    conf = df.sparkSession.conf
    now = int(re.sub(r"\D", "", conf.get(key)) or 0) if re.fullmatch(r"\d+b?", conf.get(key)) else 0
    if now <= 0 or now > size:
        conf.set(key, f"{size}b")
    return df


def plain_documents(docs: DataFrame) -> DataFrame:
    """doc_id and text only, whatever else the table carries."""
    return small_batches(docs).select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"))


def sample_labelled(labels: DataFrame, target: str, rows: int, seed: int = 17) -> DataFrame:
    """At most ``rows`` labelled ids (documented bound), chosen by a hash of the id; one label an id."""
    one = labels.where(F.col("doc_id").isNotNull() & F.col(target).isNotNull()).groupBy("doc_id").agg(F.max(target).cast("int").alias("label"))
    return one.orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(rows)
