"""A bounded, reproducible sample of labelled rows for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def crc_fold(doc_id: str, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds``; a null id is in fold 0."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % folds, F.lit(0))


def labelled_sample(
    docs: DataFrame, labels: DataFrame, label: str, train: Column, most: int, text: str = "text"
) -> DataFrame:
    """(doc_id, text, y, h) of at most ``most`` labelled ids: those with the least hash h of the id.

    ``train`` says over ``doc_id`` which ids may be learnt from. Ids labelled both ways, labels
    that are null or neither 0 nor 1, and null ids teach nothing. Only the ids are gathered
    before the texts are read, and their number is bounded, so they are broadcast.
    """
    chosen = (
        labels.select("doc_id", F.col(label).cast("int").alias("y"))
        .filter(F.col("doc_id").isNotNull() & F.col("y").isin(0, 1))
        .filter(train)
        .groupBy("doc_id")
        .agg(F.min("y").alias("y"), F.max("y").alias("_other"))
        .filter(F.col("y") == F.col("_other"))
        .select("doc_id", "y", F.xxhash64("doc_id").alias("_h"))
        .orderBy("_h", "doc_id")
        .limit(most)
        .select(F.col("doc_id").alias("_id"), "y", F.col("_h").alias("h"))
    )
    return docs.select("doc_id", F.col(text).alias("text")).join(
        F.broadcast(chosen), F.col("doc_id") == F.col("_id")
    ).select("doc_id", "text", "y", "h")
