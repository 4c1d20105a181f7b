"""The given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_all(spark: SparkSession, sf_dir: str) -> None:
    """A temporary view of each table."""
    for name in NAMES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
