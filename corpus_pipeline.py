"""A training-data pipeline of five operators; each stage works on what the one before kept.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame with the columns
of documents, the last one the encoded documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from selweave.llm import decontaminate, pieces, secrets, simhash, toxicity
from selweave.llm.common import read_table, shared_folder
from selweave.llm.queries import piece_model_path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects what the calibrated cut-off of its language flags; learns from labelled rows among its own input."""
    return toxicity.drop_toxic(docs, toxicity.fit(docs, read_table(spark, sf_dir, "labels")))


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates stays: linked fingerprints first, checked as all links are: Jaccard similarity of 0.8 or more on five-word shingles."""
    return simhash.keep_similar(docs, shingle=5, similarity=0.8)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay, their secrets are masked."""
    return secrets.redact(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids by number and digest, and the digest of the decoded text."""
    return pieces.round_trip(docs, piece_model_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", keep_one_of_each),
    ("decontamination", drop_contaminated),
    ("secret_scan", mask_secrets),
    ("piece_round_trip", encode),
]

#: Trained networks and merge tables have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written to the shared folder and read again."""
    at = f"{shared_folder(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(f"{at}/{name}")
        docs = spark.read.parquet(f"{at}/{name}")
    return docs
