"""Phase 2: similar buckets meet in bins, and ids in most of a bin's buckets become a seed group.

All steps are counts over long tables, so the order of rows, buckets and partitions never matters,
and their cost doesn't depend on how many groups come out.
"""

from __future__ import annotations

from contextlib import contextmanager
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bucketseed.functions.minhash import minhash_long, signature
from bucketseed.functions.permutations import Permutations, draw
from bucketseed.staging import staged, staged_by


def bucket_signatures(members: DataFrame, perms: Permutations, bucket: str = "bucket_id") -> DataFrame:
    """(bucket_id, size, h0, ...): minima over a bucket's ids, combined before the shuffle."""
    return minhash_long(members, bucket, "id", perms)


def make_bins(sigs: DataFrame, K: int, L: int, least: int = 2, delta: int = 1, prune: bool = True, mode: str = "text") -> DataFrame:
    """(bin_id, bin_table, bucket_id, bin_size) of bins with ``least`` or more buckets.

    ``prune`` drops bins that can't reach ``delta``: an id needs votes from over half of b buckets,
    so a group of delta ids takes delta * (b // 2 + 1) of the bin's memberships.
    """
    table = F.explode(
        F.array(
            *[
                F.struct(F.lit(l).alias("bin_table"), signature([F.col(f"h{l * K + k}") for k in range(K)], mode).alias("sig"))
                for l in range(L)
            ]
        )
    ).alias("s")
    placed = sigs.select("bucket_id", "size", table).select(
        "bucket_id", "size", "s.bin_table",
        F.concat_ws(":", F.col("s.bin_table").cast("string"), F.col("s.sig").cast("string")).alias("bin_id"),
    )
    totals = placed.groupBy("bin_id").agg(F.count("*").alias("bin_size"), F.sum("size").alias("total"))
    totals = totals.filter(F.col("bin_size") >= least)
    if prune:
        totals = totals.filter(F.col("total") >= delta * (F.floor(F.col("bin_size") / 2) + 1))
    return placed.join(totals.select("bin_id", "bin_size"), "bin_id").select("bin_id", "bin_table", "bucket_id", "bin_size")


def majority_vote(bins: DataFrame, members: DataFrame) -> DataFrame:
    """(group_id, id, votes, bin_size): ids in strictly more than half of the bin's buckets."""
    return (
        bins.select("bin_id", "bucket_id", "bin_size")
        .join(members.select("bucket_id", "id"), "bucket_id")
        .groupBy("bin_id", "bin_size", "id")
        .agg(F.count("*").alias("votes"))
        .filter(F.col("votes") * 2 > F.col("bin_size"))
        .select(F.col("bin_id").alias("group_id"), "id", "votes", "bin_size")
    )


def at_least(groups: DataFrame, delta: int) -> DataFrame:
    """Groups of ``delta`` or more ids."""
    if delta <= 1:
        return groups
    large = groups.groupBy("group_id").agg(F.count("*").alias("_n")).filter(F.col("_n") >= delta).select("group_id")
    return groups.join(large, "group_id", "left_semi")


def collapse_equal(groups: DataFrame) -> DataFrame:
    """One group (the least id) of each set of ids, found by count and two hash sums."""
    # Halved and divided so that sums of many 64-bit hashes don't overflow.
    part = lambda s: F.sum((F.xxhash64("id", F.lit(s)) / 1024).cast("bigint"))
    prints = groups.groupBy("group_id").agg(F.count("*").alias("n"), part(1).alias("a"), part(2).alias("b"))
    first = prints.groupBy("n", "a", "b").agg(F.min("group_id").alias("group_id")).select("group_id")
    return groups.join(first, "group_id", "left_semi")


def dedup_groups(groups: DataFrame, K: int, L: int = 1, seed: int = 1, singletons: str = "keep", min_size: int = 1, exact_first: bool = False, perms=None) -> DataFrame:
    """Groups vote among themselves once more, so near-equal ones become one.

    A group alone in its bin stays (``keep``) or goes by the isolated-bin rule (``drop``).
    """
    perms = perms or draw(K * L, seed)
    rows = groups.select(F.col("group_id").alias("bucket_id"), "id")
    if exact_first:
        rows = collapse_equal(groups.select("group_id", "id")).withColumnRenamed("group_id", "bucket_id")
    bins = make_bins(bucket_signatures(rows, perms), K, L, 1 if singletons == "keep" else 2, min_size, prune=False)
    return at_least(majority_vote(bins, rows), min_size)


def seed_round(members: DataFrame, K: int, L: int, delta: int, perms: Permutations, prune: bool = True) -> DataFrame:
    """Signatures, bins, vote and threshold."""
    bins = make_bins(bucket_signatures(members, perms), K, L, 2, delta, prune)
    return at_least(majority_vote(bins, members), delta)


@contextmanager
def colocated(spark: SparkSession):
    """While this holds, a join may keep rows where a part of its keys has placed them."""
    key = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(key)
    spark.conf.set(key, "false")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def local_round(members: DataFrame, K: int, L: int, delta: int, perms: Permutations, parts: int, prune: bool = True) -> DataFrame:
    """``seed_round`` within each part of the hash tables (table_id modulo ``parts``).

    Members are exchanged once, by part; signatures, bins and votes stay where that put them, as
    all their keys begin with the part. Plan and run it while ``colocated`` holds.
    """
    # never null, so that the join below adds no filter of its own and the exchange is used twice
    part, bucket = F.coalesce(F.pmod("table_id", F.lit(parts)), F.lit(0)), F.coalesce("bucket_id", F.lit(""))
    rows = members.select(part.alias("part"), bucket.alias("bucket_id"), "id").repartition(parts, "part")
    sigs = rows.groupBy("part", "bucket_id").agg(
        F.count("*").alias("size"), *[F.min(perms.of(F.col("id"), i)).alias(f"h{i}") for i in range(K * L)]
    )
    table = F.explode(
        F.array(
            *[
                F.struct(F.lit(l).alias("t"), signature([F.col(f"h{l * K + k}") for k in range(K)], "text").alias("sig"))
                for l in range(L)
            ]
        )
    ).alias("s")
    placed = sigs.select("part", "bucket_id", "size", table).select(
        "part", "bucket_id", "size",
        F.concat_ws(":", F.col("part").cast("string"), F.col("s.t").cast("string"), "s.sig").alias("bin_id"),
    )
    bin_ = Window.partitionBy("part", "bin_id")
    counted = placed.withColumns({"bin_size": F.count("*").over(bin_), "total": F.sum("size").over(bin_)}).filter("bin_size >= 2")
    if prune:
        counted = counted.filter(F.col("total") >= delta * (F.floor(F.col("bin_size") / 2) + 1))
    votes = (
        counted.select("part", "bucket_id", "bin_id", "bin_size")
        .join(rows, ["part", "bucket_id"])
        .groupBy("part", "bin_id", "bin_size", "id")
        .agg(F.count("*").alias("votes"))
        .filter(F.col("votes") * 2 > F.col("bin_size"))
    )
    large = votes.withColumn("_n", F.count("*").over(Window.partitionBy("part", "bin_id"))).filter(F.col("_n") >= delta)
    return large.select(F.col("bin_id").alias("group_id"), "id", "votes", "bin_size")


def similar_bucket_seeds(
    members: DataFrame,
    K: int = 3,
    L: int = 20,
    delta: int = 10,
    seed: int = 0,
    vote: str = "global",
    parts: int = 4,
    batches: int | None = None,
    prune: bool = True,
    dedup: bool = True,
    singletons: str = "keep",
    kind: str = "affine",
) -> DataFrame:
    """(group_id, id, votes, bin_size): the seed groups of ``members``.

    ``vote='local'`` votes part by part; ``batches`` seeds ranges of tables one after another, each
    batch written before the next is read, so that no more than one is in flight. Both end with the
    near-duplicate round over all groups. Affine permutations need ids below 2^31 - 1; ``xx`` takes
    any id.
    """
    first, second = draw(K * L, seed, kind), draw(K, seed + 1, kind)
    if batches:
        # a folder for each batch: a batch reads its own members alone
        split = staged_by(members.withColumn("_batch", F.pmod("table_id", F.lit(batches)).cast("int")), "_batch", "batches")
        groups = reduce(
            DataFrame.unionByName,
            [
                staged(
                    seed_round(split.filter(F.col("_batch") == b), K, L, delta, first, prune)
                    .withColumn("group_id", F.concat_ws("/", F.lit(str(b)), "group_id")),
                    "batch",
                )
                for b in range(batches)
            ],
        )
    elif vote == "local":
        with colocated(members.sparkSession):
            groups = staged(local_round(members, K, L, delta, first, parts, prune), "local")
    else:
        groups = seed_round(members, K, L, delta, first, prune)
    if not dedup:
        return groups
    return dedup_groups(staged(groups, "groups"), K, 1, seed + 1, singletons, perms=second)


def seed_stats(raw: DataFrame, kept: DataFrame, final: DataFrame) -> DataFrame:
    """One row: groups at each step, ids in the final groups (with repeats), and the final count."""
    count = lambda df, name: df.agg(F.count_distinct("group_id").alias(name))
    return (
        count(raw, "raw_groups")
        .crossJoin(count(kept, "large_groups"))
        .crossJoin(final.agg(F.count_distinct("group_id").alias("seeds"), F.count("*").alias("seed_ids")))
    )
