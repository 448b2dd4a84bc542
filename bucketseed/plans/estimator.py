"""The method as a pyspark.ml estimator: ``fit`` seeds and centers, ``transform`` assigns."""

from __future__ import annotations

import json

from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketseed.operators.assign import assign_blocks, collected
from bucketseed.operators.transform import DatasetSpec
from bucketseed.plans.threephase import cluster_dense, cluster_hetero, cluster_sparse


class BucketSeedClusterer(Estimator):
    """``spec`` names the columns; ``params`` go to the plan of its kind.

    A mixed table's numeric cuts are ranks of the fitted rows, so its model assigns token rows.
    """

    def __init__(self, spec: DatasetSpec, **params):
        super().__init__()
        self.spec, self.settings = spec, params

    def _fit(self, dataset: DataFrame) -> BucketSeedModel:
        spec = self.spec.check(dataset)
        rows = dataset.withColumn("id", F.col(spec.id_col).cast("bigint"))
        if spec.kind == "dense":
            run = cluster_dense(rows.select("id", F.col(spec.vec_col).alias("vec")), **self.settings)
            dist, column = "euclidean", "vec"
        elif spec.kind == "sparse":
            run = cluster_sparse(rows.select("id", F.col(spec.tokens_col).alias("tokens")), **self.settings)
            dist, column = "jaccard_tokens", "modes"
        else:
            run = cluster_hetero(rows, list(spec.numeric), list(spec.categorical), **self.settings)
            dist, column = "jaccard_tokens", "modes"
        model = BucketSeedModel(run.centers.select("seed_id", F.col(column).alias("center"), "size"), spec, self.settings, dist)
        model.summary = run
        return model


class BucketSeedModel(Model):
    def __init__(self, centers: DataFrame, spec: DatasetSpec, settings: dict, dist: str):
        super().__init__()
        self.centers, self.spec, self.settings, self.dist = centers, spec, settings, dist
        self.summary = None

    def _rows(self, dataset: DataFrame) -> tuple[DataFrame, str]:
        from bucketseed.functions.doph import doph
        from bucketseed.operators.transform import coordinate_tokens

        rows = dataset.withColumn("id", F.col(self.spec.id_col).cast("bigint"))
        if self.spec.kind == "dense":
            return rows.select("id", F.col(self.spec.vec_col).alias("vec")), "vec"
        if self.spec.kind == "sparse":
            coords = doph(rows, self.spec.tokens_col, self.settings.get("D", 400), self.settings.get("seed", 0), self.settings.get("densify", "rotation"))
            return coords.select("id", coordinate_tokens("coords").alias("tokens")), "tokens"
        return rows.select("id", "tokens"), "tokens"

    def _transform(self, dataset: DataFrame) -> DataFrame:
        rows, column = self._rows(dataset)
        return assign_blocks(rows, *collected(self.centers, "center"), self.dist, column)

    def save(self, path: str) -> None:
        """Centers as Parquet and the rest as one line of JSON, in the folder ``path``."""
        meta = {"spec": {k: v for k, v in self.spec.__dict__.items()}, "settings": self.settings, "dist": self.dist}
        spark = self.centers.sparkSession
        self.centers.write.mode("overwrite").parquet(f"{path}/centers")
        spark.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> BucketSeedModel:
        meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
        spec = {k: tuple(v) if isinstance(v, list) else v for k, v in meta["spec"].items()}
        return BucketSeedModel(spark.read.parquet(f"{path}/centers"), DatasetSpec(**spec), meta["settings"], meta["dist"])
