"""Readers with declared schemas, set-per-row text, and sinks for phases."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc, parquet or text; a schema is required where the format carries none."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a declared schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def read_sparse_text(spark: SparkSession, path: str) -> DataFrame:
    """Lines of ``id idx:val idx:val ...`` as (id, tokens, weights map); bad pairs are dropped."""
    parts = F.split(F.trim("value"), r"\s+")
    pairs = F.filter(F.slice(parts, 2, 1 << 30), lambda p: p.rlike(r"^\d+:[^:]+$"))
    entries = F.transform(
        pairs,
        lambda p: F.struct(F.split(p, ":")[0].cast("bigint").alias("key"), F.split(p, ":")[1].try_cast("double").alias("value")),
    )
    rows = spark.read.text(path).filter(F.trim("value") != "")
    weights = F.map_from_entries(F.filter(entries, lambda e: e["value"].isNotNull()))
    return rows.select(parts[0].cast("bigint").alias("id"), weights.alias("weights")).select(
        "id", F.sort_array(F.map_keys("weights")).alias("tokens"), "weights"
    )


def write_phase(df: DataFrame, path: str, name: str, partition_by: str | None = None) -> str:
    """Parquet of one phase, partitioned if asked (members by table, for batches)."""
    writer = df.write.mode("overwrite")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(f"{path}/{name}")
    return f"{path}/{name}"


def write_bucketed(df: DataFrame, table: str, key: str = "bucket_id", buckets: int = 64) -> None:
    """A table bucketed by ``key``: the vote's join then has no exchange on this side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
