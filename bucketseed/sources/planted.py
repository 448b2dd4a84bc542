"""Planted data with known clusters; all noise comes from hashes, so reruns agree."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def unit(seed: int, *cols: Column) -> Column:
    return (F.shiftrightunsigned(F.xxhash64(F.lit(seed), *cols), 11) + F.lit(0.5)) / F.lit(float(1 << 53))


def normal(seed: int, *cols: Column) -> Column:
    """Box-Muller on two hashes."""
    return F.sqrt(-2 * F.log(unit(seed, *cols))) * F.cos(2 * math.pi * unit(seed + 1, *cols))


def _truth(spark: SparkSession, n: int, k: int, seed: int) -> DataFrame:
    return spark.range(n).select("id", F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(k)).alias("truth"))


def planted_gauss(spark: SparkSession, n: int, k: int, dims: int, noise: float, seed: int = 0, scale: int = 1_000_000) -> DataFrame:
    """(id, vec fixed point, truth): balls around uniform centers of the unit cube."""
    at = lambda i: F.floor((unit(seed + 7, F.col("truth"), F.lit(i)) + noise * normal(seed + 11, F.col("id"), F.lit(i))) * scale).cast("bigint")
    return _truth(spark, n, k, seed).select("id", F.array(*[at(i) for i in range(dims)]).alias("vec"), "truth")


def planted_sets(spark: SparkSession, n: int, k: int, size: int = 60, flip: float = 0.05, seed: int = 0) -> DataFrame:
    """(id, tokens, truth): base sets with a share of tokens replaced."""
    token = lambda i: F.when(
        unit(seed + 3, F.col("id"), i) < flip, F.pmod(F.xxhash64(F.lit(seed + 5), F.col("id"), i), F.lit(1 << 28))
    ).otherwise(F.pmod(F.xxhash64(F.lit(seed + 9), F.col("truth"), i), F.lit(1 << 28)))
    tokens = F.sort_array(F.array_distinct(F.transform(F.sequence(F.lit(1), F.lit(size)), token)))
    return _truth(spark, n, k, seed).select("id", tokens.alias("tokens"), "truth")


def planted_mixed(spark: SparkSession, n: int, k: int, noise: float = 0.01, flip: float = 0.05, seed: int = 0) -> DataFrame:
    """(id, x, y, a, b, c, truth): centers and categories by truth, some categories flipped."""
    number = lambda i: unit(seed + 7, F.col("truth"), F.lit(i)) + noise * normal(seed + 11, F.col("id"), F.lit(i))
    category = lambda i: F.when(
        unit(seed + 3, F.col("id"), F.lit(i)) < flip, F.pmod(F.xxhash64(F.lit(seed + 5), F.col("id"), F.lit(i)), F.lit(8))
    ).otherwise(F.pmod(F.xxhash64(F.lit(seed + 9), F.col("truth"), F.lit(i)), F.lit(8))).cast("string")
    return _truth(spark, n, k, seed).select(
        "id", number(0).alias("x"), number(1).alias("y"), category(2).alias("a"), category(3).alias("b"), category(4).alias("c"), "truth"
    )


def planted_skew(spark: SparkSession, n: int, share: float = 0.3, seed: int = 0) -> DataFrame:
    """(id, tokens): a share of rows holds one and the same set."""
    own = F.transform(F.sequence(F.lit(1), F.lit(20)), lambda i: F.pmod(F.xxhash64(F.lit(seed), F.col("id"), i), F.lit(1 << 28)))
    same = F.array(*[F.lit(i * 1000 + 1).cast("bigint") for i in range(20)])
    return spark.range(n).select("id", F.when(unit(seed + 1, F.col("id")) < share, same).otherwise(own).alias("tokens"))


def register_data_source(spark: SparkSession) -> str:
    """Registers ``planted`` as a format: options rows, clusters, dims, noise, seed."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.n, self.k = int(options.get("rows", "1000")), int(options.get("clusters", "10"))
            self.dims, self.noise = int(options.get("dims", "8")), float(options.get("noise", "0.05"))
            self.seed = int(options.get("seed", "0"))

        def partitions(self):
            step = -(-self.n // 8)
            return [InputPartition((a, min(a + step, self.n))) for a in range(0, self.n, step)]

        def read(self, partition):
            import random

            for i in range(*partition.value):
                own = random.Random(self.seed * 1_000_003 + i)
                truth = own.randrange(self.k)
                center = random.Random(f"{self.seed}/{truth}")
                yield i, [center.random() + own.gauss(0, self.noise) for _ in range(self.dims)], truth

    class Planted(DataSource):
        @classmethod
        def name(cls):
            return "planted"

        def schema(self):
            return "id bigint, vec array<double>, truth bigint"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(Planted)
    return "planted"
