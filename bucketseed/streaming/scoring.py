"""Streams of rows against a fitted model; centers are fixed after seeding, so scoring is narrow."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketseed.operators.assign import assign_blocks


def read_stream(spark: SparkSession, path: str, schema, event_time: str | None = None, files: int | None = 100) -> DataFrame:
    """A Parquet folder as a stream; a time without zone is cast, as watermarks need a timestamp.

    ``files=None`` reads what is there as one batch, within which no row is late.
    """
    reader = spark.readStream.schema(schema)
    rows = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(path)
    return rows.withColumn(event_time, F.col(event_time).cast("timestamp")) if event_time else rows


def assign_stream(stream: DataFrame, ids: np.ndarray, centers: np.ndarray, dist: str = "euclidean", vec: str = "vec") -> DataFrame:
    """(id, cluster_id, dist) of a stream: stateless, one broadcast model."""
    return assign_blocks(stream, ids, centers, dist, vec)


def windowed(stream: DataFrame, time: str, key: str, length: str, slide: str | None = None, late: str = "1 hour", value: str | None = None) -> DataFrame:
    """Counts (and the largest ``value``) by tumbling or sliding window; late rows drop by watermark."""
    w = F.window(time, length, slide) if slide else F.window(time, length)
    aggs = [F.count("*").alias("n")] + ([F.max(value).alias("most")] if value else [])
    return stream.withWatermark(time, late).groupBy(w.alias("w"), key).agg(*aggs).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, *[c for c in ("n", "most") if c == "n" or value]
    )


def sessions(stream: DataFrame, time: str, key: str, gap: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("w"), key).agg(F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n"
    )


def deduplicated(stream: DataFrame, time: str, keys: list[str], late: str = "1 day") -> DataFrame:
    """First rows of each fingerprint within the watermark."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def drift(stream: DataFrame, key: str, value: str, limit: float) -> DataFrame:
    """(key, n, mean, alarm) per batch: running mean of each cluster, alarm above ``limit`` times it."""

    def step(k, batches, state):
        n, total = state.get if state.exists else (0, 0.0)
        import pandas as pd

        alarm = False
        for pdf in batches:
            for v in pdf[value]:
                alarm = alarm or (n > 0 and v > limit * total / n)
                n, total = n + 1, total + float(v)
        state.update((n, total))
        yield pd.DataFrame({key: [k[0]], "n": [n], "mean": [total / max(n, 1)], "alarm": [bool(alarm)]})

    kind = dict(stream.dtypes)[key]
    return stream.groupBy(key).applyInPandasWithState(
        step, f"{key} {kind}, n bigint, mean double, alarm boolean", "n bigint, total double", "update", "NoTimeout"
    )


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, within: str, late: str = "1 hour") -> DataFrame:
    """Rows of ``right`` that follow a row of ``left`` with the same key within an interval."""
    a = left.withWatermark(left_time, late).alias("a")
    b = right.withWatermark(right_time, late).alias("b")
    on = (
        (F.col(f"a.{key}") == F.col(f"b.{key}"))
        & (F.col(f"b.{right_time}") >= F.col(f"a.{left_time}"))
        & (F.col(f"b.{right_time}") <= F.col(f"a.{left_time}") + F.expr(f"INTERVAL {within}"))
    )
    return a.join(b, on)


def reseeding(stream: DataFrame, seed_fn, path: str, checkpoint: str):
    """Each batch is added to the rows in ``path`` and ``seed_fn(all rows)`` seeds them anew."""

    def each(batch: DataFrame, epoch: int):
        batch.write.mode("overwrite").parquet(f"{path}/batch={epoch}")
        seed_fn(batch.sparkSession.read.parquet(path)).write.mode("overwrite").parquet(f"{path}-seeds/{epoch}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drained(stream: DataFrame, spark: SparkSession, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its rows.

    Appended rows go to files in the shared folder; results that later batches change (``complete``,
    ``update``) are kept by the driver, so they must be small.
    """
    from bucketseed.staging import shared_dir

    out = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{shared_dir(spark)}/streams/{name}").trigger(availableNow=True)
    if mode == "append":
        path = f"{shared_dir(spark)}/bucketseed/{name}"
        out.format("parquet").option("path", path).option("compression", "zstd").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    out.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)
