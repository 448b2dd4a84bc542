"""Phase 3, first half: one central vector for each seed group."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.operators.ranking import ranked

#: Groups of up to this many rows are brought together as they are; larger ones are counted before they move.
GROUP_ROWS = 2_000


def numbered(groups: DataFrame) -> DataFrame:
    """Adds ``seed_id`` by the order of group ids: one row per group is ranked, not per member."""
    seeds = ranked(groups.select("group_id").distinct(), ["group_id"], ["group_id"])
    return groups.join(seeds.select("group_id", (F.col("rank") + 1).alias("seed_id")), "group_id")


def rounded_mean(total: Column, n: Column) -> Column:
    """floor(total / n + 1/2) in exact integers, for fixed-point sums."""
    return F.floor((2 * total + n) / (2.0 * n)).cast("bigint")


def centroids(groups: DataFrame, data: DataFrame, vec: str = "vec", dims: int | None = None, exact: bool = True) -> DataFrame:
    """(seed_id, vec, size): means over a group's ids, summed before and after the exchange.

    ``exact`` rounds fixed-point means to integers, so that all engines agree.
    """
    dims = dims or len(data.select(vec).first()[0])
    rows = groups.select("seed_id", "id").join(data.select("id", vec), "id")
    sums = rows.groupBy("seed_id").agg(
        F.count("*").alias("size"), *[F.sum(F.get(vec, F.lit(i))).alias(f"s{i}") for i in range(dims)]
    )
    mean = (lambda i: rounded_mean(F.col(f"s{i}"), F.col("size"))) if exact else (lambda i: F.col(f"s{i}") / F.col("size"))
    return sums.select("seed_id", F.array(*[mean(i) for i in range(dims)]).alias("vec"), "size")


def modes(groups: DataFrame, data: DataFrame, tokens: str = "tokens") -> DataFrame:
    """(seed_id, modes, size): each coordinate's most frequent value, ties to the least."""
    sizes = groups.groupBy("seed_id").agg(F.count("*").alias("size"))
    large = [r["seed_id"] for r in sizes.filter(F.col("size") > GROUP_ROWS).select("seed_id").collect()]
    rows = groups.select("seed_id", "id").join(data.select("id", F.col(tokens).alias("tokens")), "id").select("seed_id", "tokens")
    if not large:
        return _packed_modes(rows)
    # at most one in GROUP_ROWS of the members
    few = F.broadcast(groups.sparkSession.createDataFrame([(i,) for i in large], "seed_id bigint"))
    return _packed_modes(rows.join(few, "seed_id", "left_anti")).unionByName(_counted_modes(rows.join(few, "seed_id", "left_semi")))


def _counted_modes(rows: DataFrame) -> DataFrame:
    """``modes`` of (seed_id, tokens) by counts that combine before the exchange, for groups of any size."""
    sizes = rows.groupBy("seed_id").agg(F.count("*").alias("size"))
    best = (
        rows.select("seed_id", F.posexplode("tokens").alias("pos", "value"))
        .groupBy("seed_id", "pos", "value")
        .agg(F.count("*").alias("n"))
        .groupBy("seed_id", "pos")
        .agg(F.max(F.struct("n", (-F.col("value")).alias("neg"))).alias("top"))
        .groupBy("seed_id")
        .agg(F.array_sort(F.collect_list(F.struct("pos", (-F.col("top.neg")).alias("value")))).alias("all"))
    )
    return best.join(sizes, "seed_id").select("seed_id", F.transform("all", lambda x: x["value"]).alias("modes"), "size")


def column_modes(x: np.ndarray) -> np.ndarray:
    """Most frequent values over axis 1 of (group, row, coordinate), ties to the least."""
    if x.shape[1] <= 2:
        return x.min(1)
    x = np.sort(x, axis=1)
    value, run = x[:, 0].copy(), np.ones(x[:, 0].shape, np.int32)
    most = run.copy()
    for i in range(1, x.shape[1]):
        run = np.where(x[:, i] == x[:, i - 1], run + 1, 1)
        better = run > most
        value[better], most[better] = x[:, i][better], run[better]
    return value


def _packed_modes(rows: DataFrame) -> DataFrame:
    """``modes`` of (seed_id, tokens): whole rows meet by group, in one exchange of a row each."""

    def found(seeds, x):
        first = np.flatnonzero(np.concatenate([[True], seeds[1:] != seeds[:-1]]))
        sizes = np.diff(np.append(first, len(seeds)))
        out = np.empty((len(first), x.shape[1]), np.int64)
        for size in np.unique(sizes):
            same = np.flatnonzero(sizes == size)
            out[same] = column_modes(x[first[same][:, None] + np.arange(size)])
        offsets = pa.array(np.arange(len(first) + 1, dtype=np.int32) * x.shape[1])
        values = pa.ListArray.from_arrays(offsets, pa.array(out.ravel()))
        return pa.RecordBatch.from_arrays([pa.array(seeds[first]), values, pa.array(sizes)], ["seed_id", "modes", "size"])

    def run(batches):
        seeds, held = [], []  # rows of the group that the next batch may go on with
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            own = batch.column("seed_id").to_numpy()
            x = batch.column("tokens").flatten().to_numpy(zero_copy_only=False).reshape(n, -1)
            last = int(np.searchsorted(own, own[-1]))
            if last or (seeds and seeds[0][0] != own[-1]):
                yield found(np.concatenate([*seeds, own[:last]]), np.concatenate([*held, x[:last]]))
                seeds, held = [], []
            seeds.append(own[last:])
            held.append(x[last:])
        if seeds:
            yield found(np.concatenate(seeds), np.concatenate(held))

    narrow = rows.select(F.col("seed_id").cast("bigint").alias("seed_id"), "tokens").repartition("seed_id").sortWithinPartitions("seed_id")
    return narrow.mapInArrow(run, "seed_id bigint, modes array<bigint>, size bigint")
