"""Parquet access to the given tables, through Spark readers only."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

NAMES = (
    "region nation customer supplier part orders lineitem events documents "
    "embeddings pages benchmark labels conversations"
).split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table of ``sf_dir``; any path that Spark can read will do."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views over all tables, for SQL users."""
    for name in NAMES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
