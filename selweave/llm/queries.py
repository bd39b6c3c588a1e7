"""Queries of the training-data operators, over whole tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .common import read_table

Query = Callable[[SparkSession, str], DataFrame]


def piece_model_path() -> str:
    """Where the public piece model lies; operators take the path as a parameter."""
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import toxicity as op

    docs = read_table(spark, sf_dir, "documents")
    return op.score(docs, op.fit(docs, read_table(spark, sf_dir, "labels")))


def quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality_classifier as op

    docs = read_table(spark, sf_dir, "documents")
    return op.score(docs, op.fit(docs, read_table(spark, sf_dir, "labels")))


def secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import secrets as op

    return op.scan(read_table(spark, sf_dir, "documents"))


def piece_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import pieces as op

    return op.round_trip(read_table(spark, sf_dir, "documents"), piece_model_path())


def quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality_rules as op

    docs = read_table(spark, sf_dir, "documents")
    return op.judge(docs, op.fit(docs, read_table(spark, sf_dir, "labels")))


def suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import suffix_dedup as op

    return op.remove_repeats(read_table(spark, sf_dir, "documents"))


def attention_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import lm as op

    return op.score(spark, read_table(spark, sf_dir, "documents"), piece_model_path())


def chained_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import chains as op

    return op.shared_passages(read_table(spark, sf_dir, "documents"))


def near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import simhash as op

    return op.near_duplicates(read_table(spark, sf_dir, "documents"))


def decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import decontaminate as op

    return op.find_items(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def queries() -> dict[str, Query]:
    return {
        "op1_toxicity": toxicity,
        "op2_chained_passages": chained_passages,
        "op3_suffix_dedup": suffix_dedup,
        "op4_attention_lm": attention_lm,
        "op5_simhash": near_duplicates,
        "op6_quality_rules": quality_rules,
        "op7_quality_classifier": quality_classifier,
        "op8_secret_scan": secret_scan,
        "op9_piece_round_trip": piece_round_trip,
        "op10_decontamination": decontamination,
    }


def oracle_sql() -> dict[str, str]:
    return {}
