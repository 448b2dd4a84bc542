"""Exact ranks of a distributed sort: no task holds more than one range of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.staging import staged

_WITHIN = (1 << 33) - 1


def ranked(df: DataFrame, order: list[str], keep: list[str], group: list[str] = ()) -> DataFrame:
    """(*group, *keep, rank, total): each row's place by ``order`` in its group, from 0, and the group's size.

    Rows are range-partitioned and sorted once; a row's place in its range is written beside it, so
    a lost task can't move it, and only one count for each group and range is added up.
    """
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by = [*group, *order]
    ordered = staged(
        df.repartitionByRange(parts, *by)
        .sortWithinPartitions(*by)
        .select(
            *group,
            *[c for c in keep if c not in group],
            F.spark_partition_id().alias("_p"),
            F.monotonically_increasing_id().bitwiseAND(F.lit(_WITHIN)).alias("_i"),
        ),
        "ranges",
    )
    counts = ordered.groupBy(*group, "_p").agg(F.count("*").alias("_n"), F.min("_i").alias("_first"))
    if group:
        before = Window.partitionBy(*group).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
        offsets = counts.select(
            *group,
            "_p",
            (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_before"),
            F.sum("_n").over(Window.partitionBy(*group)).alias("total"),
        )
    else:
        rows, at, found = sorted(counts.collect(), key=lambda r: r["_p"]), 0, []  # one row a partition
        total = sum(r["_n"] for r in rows)
        for r in rows:
            found.append((r["_p"], at - r["_first"], total))
            at += r["_n"]
        offsets = df.sparkSession.createDataFrame(found, "_p int, _before bigint, total bigint")
    # one row for each group and range that holds it: at most groups + ranges of them
    return ordered.join(F.broadcast(offsets), [*group, "_p"]).select(
        *group, *[c for c in keep if c not in group], (F.col("_before") + F.col("_i")).alias("rank"), "total"
    )
