"""Parameter grids and bands of k*: the best run of each band."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def combinations(**values: list) -> list[dict]:
    names = list(values)
    return [dict(zip(names, v, strict=True)) for v in itertools.product(*values.values())]


def grid_search(spark: SparkSession, run, grid: list[dict]) -> DataFrame:
    """(params, k_star, mean_radius, seconds): ``run(**params)`` gives a dict of the last three."""
    rows = []
    for params in grid:
        got = run(**params)
        rows.append((", ".join(f"{k}={v}" for k, v in params.items()), int(got["k_star"]), float(got["mean_radius"]), float(got["seconds"])))
    return spark.createDataFrame(rows, "params string, k_star bigint, mean_radius double, seconds double")


def best_by_band(results: DataFrame, bands: list[int], by: str = "mean_radius") -> DataFrame:
    """The best row of each k* band [bands[i], bands[i+1])."""
    band = sum(((F.col("k_star") >= b).cast("int") for b in bands), F.lit(0))
    w = Window.partitionBy("band").orderBy(by, "seconds", "params")
    return results.withColumn("band", band).withColumn("_r", F.row_number().over(w)).filter("_r = 1").drop("_r")
