"""Nearest-neighbour lookup over the hash tables, and exact pair search for ground truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.functions.distances import distance
from bucketseed.functions.minhash import minhash_values
from bucketseed.functions.permutations import draw
from bucketseed.functions.projection import dot
from bucketseed.operators.postings import near_sets, similar_pairs


def top_c(pairs: DataFrame, top: int, order: str = "dist") -> DataFrame:
    w = Window.partitionBy("qid").orderBy(order, "id")
    return pairs.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= top)


def minhash_nns(base: DataFrame, queries: DataFrame, K: int, L: int, top: int, seed: int = 0, perms=None) -> DataFrame:
    """(qid, id, dist, rank): the union of a query's L buckets, re-ranked by exact Jaccard.

    Queries are broadcast with their hash values, in chunks; each task keeps its nearest rows of a query.
    """
    hashed = lambda df, who: df.select(who, "tokens", minhash_values("tokens", perms or draw(K * L, seed)).alias("h"))
    return top_c(near_sets(hashed(base, "id"), hashed(queries, "qid"), top, tables=L), top)


def collision_counts(base: DataFrame, queries: DataFrame, directions: list, width, vec: str = "vec") -> DataFrame:
    """(qid, id, collisions): tables in which id is within w/2 of the query's projection.

    The anchor bucket is centred on the query; the range join is an equi-join on cells of width
    w/2 and a residual test. Works on fixed-point vectors and integer directions exactly.
    """
    hs = F.array(*[dot(vec, d) for d in directions])
    cell = F.floor(F.col("h") * 2 / F.lit(width))
    b = base.select("id", F.posexplode(hs).alias("table_id", "h")).withColumn("cell", cell)
    q = (
        queries.select("qid", F.posexplode(hs).alias("table_id", "h"))
        .withColumn("cell", F.explode(F.sequence(cell - 1, cell + 1)))
        .withColumnRenamed("h", "qh")
    )
    return (
        q.join(b, ["table_id", "cell"])
        .filter(2 * F.abs(F.col("h") - F.col("qh")) <= F.lit(width))
        .groupBy("qid", "id")
        .agg(F.count("*").alias("collisions"))
    )


def qalsh_nns(base: DataFrame, queries: DataFrame, directions: list, width, threshold: int, top: int, vec: str = "vec") -> DataFrame:
    """(qid, id, dist, rank): ids with more than ``threshold`` collisions, by exact distance."""
    found = collision_counts(base, queries, directions, width, vec).filter(F.col("collisions") > threshold)
    near = (
        found.join(base.select("id", F.col(vec).alias("_v")), "id")
        .join(queries.select("qid", F.col(vec).alias("_q")), "qid")
        .select("qid", "id", distance("euclidean")(F.col("_v"), F.col("_q")).alias("dist"))
    )
    return top_c(near, top)


def exact_pairs(df: DataFrame, least: float, tokens: str = "tokens") -> DataFrame:
    """(a, b, jaccard) of all pairs that share a token and reach ``least``, over broadcast chunks of an inverted index."""
    return similar_pairs(df.select("id", F.col(tokens).alias("tokens")), least)


def similarity_join(left: DataFrame, right: DataFrame, least: float) -> DataFrame:
    """(qid, id, jaccard) of all pairs that reach ``least``, on whole sets; ``left`` is broadcast in chunks."""
    near = near_sets(right.select("id", "tokens"), left, least=least)
    return near.select("qid", "id", (1 - F.col("dist")).alias("jaccard"))
