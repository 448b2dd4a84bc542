"""A training-data pipeline in five stages over ``documents``, each one corpus operator.

Each stage takes (spark, docs, sf_dir), works on all rows it is given and returns a DataFrame, which
is written as Parquet and read again as the next stage's ``docs``. All but the last return the
columns of ``documents``.

Defined results: stages judge rows, so rows that share an id or have none are told apart by their
texts; a null or empty text is never toxic by its terms, a copy, contaminated or personal; a row
that repeats another is its copy; texts are read whole, however long; extra columns are carried,
and mixing replaces those named copy, rate or shuffle_key; empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketseed.llm import factorization, identifiers, near_duplicates, poisson_mix, winnowing
from bucketseed.staging import staged
from bucketseed.tables import load


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorization machine scores below one half."""
    model = factorization.fit(docs, load(spark, sf_dir, "labels"), F.lit(True))
    return factorization.without_toxic(docs, model)


def deduplication(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: of equal ids, the earlier row."""
    return near_duplicates.one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark."""
    return winnowing.uncontaminated(docs, load(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, their identifiers replaced by kinds; ``n_chars`` follows the new text."""
    found = identifiers.find_identifiers(docs, identifiers.fit(docs), redacted=True)
    clean = found.select(docs.columns)
    if "n_chars" not in docs.columns:
        return clean
    changed = F.when(F.size(found["spans"]) > 0, F.length("text").cast("bigint")).otherwise(F.col("n_chars"))
    return found.withColumn("n_chars", changed).select(docs.columns)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated to their sources' target weights, in a global random order."""
    return poisson_mix.replicate(docs, poisson_mix.WEIGHTS)


STAGES = [
    ("toxicity", toxicity),
    ("deduplication", deduplication),
    ("decontamination", decontamination),
    ("personal data", personal_data),
    ("mixing", mixing),
]

#: The learnt stages can't be expressed in SQL; tests/llm/test_pipeline.py holds all five against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows that all stages leave of ``documents``."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = staged(docs, name.replace(" ", "-"))
    return docs
