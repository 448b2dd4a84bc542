"""The data sets of the experiments, built from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketseed.functions import features as ft
from bucketseed.staging import spread
from bucketseed.tables import load


def _texts(spark: SparkSession, d: str) -> DataFrame:
    return spread(load(spark, d, "documents").select("doc_id", "text"))


def docs_sets(spark: SparkSession, d: str) -> DataFrame:
    return _texts(spark, d).select(F.col("doc_id").alias("id"), ft.word_set("text").alias("tokens"))


def page_sets(spark, d):
    return spread(load(spark, d, "pages").select("page_id", "html")).select(F.col("page_id").alias("id"), ft.html_tokens("html").alias("tokens"))


def turn_sets(spark, d):
    return spread(load(spark, d, "conversations").select("conv_id", "turn", "text")).select(
        (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), ft.word_set("text").alias("tokens")
    )


def basket_sets(spark, d):
    return ft.baskets(load(spark, d, "orders"), load(spark, d, "lineitem"))


def embedding_rows(spark, d):
    return spread(load(spark, d, "embeddings").select("vec_id", "embedding")).select(F.col("vec_id").alias("id"), ft.fixed_point("embedding").alias("vec"))


def letter_rows(spark, d):
    """Letter shares in fixed point by the same double arithmetic as the SQL twin."""
    rows = _texts(spark, d).select(F.col("doc_id").alias("id"), ft.letter_histogram("text").alias("c"))
    total = F.aggregate("c", F.lit(0).cast("bigint"), lambda s, x: s + x)
    return rows.withColumn("n", total).select(
        "id",
        F.transform(
            "c", lambda x: F.when(F.col("n") > 0, F.floor(x * F.lit(1000000.0) / F.col("n"))).otherwise(F.lit(0)).cast("bigint")
        ).alias("vec"),
    )


def lineitem_rows(spark, d):
    fixed = lambda c, k: F.floor(F.col(c) * F.lit(k) + F.lit(0.5)).cast("bigint")
    vec = F.array(fixed("l_quantity", 20000.0), fixed("l_extendedprice", 10.0), fixed("l_discount", 10000000.0), fixed("l_tax", 12500000.0))
    numeric = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    return ft.with_row_id(load(spark, d, "lineitem"), keep=numeric).select("id", vec.alias("vec"))


#: Five numeric and four categorical attributes.
NINE = (
    ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice"],
    ["l_returnflag", "l_linestatus", "o_orderpriority", "p_type"],
)


def nine_attributes(spark, d):
    own = [c for c in [*NINE[0], *NINE[1]] if c.startswith("l_")]
    rows = ft.with_row_id(load(spark, d, "lineitem"), keep=["l_orderkey", "l_partkey", *own])
    return (
        rows.join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(load(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
        .select("id", *NINE[0], *NINE[1])
    )


EVENT = (["value", "hour", "k"], ["event_type"])


def event_records(spark, d):
    return load(spark, d, "events").select(
        F.col("event_id").alias("id"),
        "value",
        F.hour("ts").cast("bigint").alias("hour"),
        ft.json_field("props", "k").cast("bigint").alias("k"),
        "event_type",
    )


ORDER = (["o_totalprice", "c_acctbal"], ["o_orderstatus", "o_orderpriority", "c_mktsegment", "c_nationkey"])


def order_records(spark, d):
    return (
        load(spark, d, "orders")
        .join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
        .select(F.col("o_orderkey").alias("id"), *ORDER[0], *ORDER[1])
    )
