"""Queries of the corpus operators, one for each, and their SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, chat, decontaminate, langid, pii, quality, secrets, simhash, token_count, toxicity
from .common import read_table


def _documents(operator: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: operator(read_table(spark, sf_dir, "documents"))


def _pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_toxicity": toxicity.toxicity,
        "op2_benchmark_decontamination": lambda spark, sf_dir: decontaminate.contaminations(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")),
        "op3_bpe_encoding": _documents(bpe.encoding_report),
        "op4_secret_scan": _documents(secrets.secret_report),
        "op5_pii": _documents(pii.pii_report),
        "op6_simhash_near_dedup": _documents(simhash.near_duplicates),
        "op7_language_id": langid.identify,
        "op8_chat_formatting": chat.format_conversations,
        "op9_token_counts": _documents(token_count.token_counts),
        "op10_quality_rules": _documents(quality.quality_report),
        "pipeline": _pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op4_secret_scan": secrets.secrets_sql(),
        "op8_chat_formatting": chat.FORMAT_SQL,
        "op10_quality_rules": quality.quality_sql(),
    }
