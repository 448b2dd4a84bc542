"""Cost and compactness measures."""

from __future__ import annotations

import re
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(df: DataFrame) -> float:
    """Wall seconds of computing ``df`` into the noop sink."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


class PhaseTimer:
    """Seconds by phase name: ``with timer('seed'): ...``."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    def __call__(self, name: str):
        self._name = name
        return self

    def __enter__(self):
        self._began = time.perf_counter()

    def __exit__(self, *_):
        self.seconds[self._name] = self.seconds.get(self._name, 0.0) + time.perf_counter() - self._began


def repeat(fn, times: int = 5) -> dict:
    """Means of the dicts that ``fn(seed)`` gives for seeds 0, 1, ..."""
    runs = [fn(s) for s in range(times)]
    return {k: sum(r[k] for r in runs) / times for k in runs[0]}


def radii(assigned: DataFrame) -> DataFrame:
    """(cluster_id, size, radius): the largest member distance of each cluster."""
    return assigned.groupBy("cluster_id").agg(F.count("*").alias("size"), F.max("dist").alias("radius"))


def radius_summary(assigned: DataFrame) -> DataFrame:
    """One row: k_star, n, n_over_k, mean, max and size-weighted radius, total distance."""
    per = assigned.groupBy("cluster_id").agg(
        F.count("*").alias("size"), F.max("dist").alias("radius"), F.sum("dist").alias("total")
    )
    return per.agg(
        F.count("*").alias("k_star"),
        F.sum("size").alias("n"),
        (F.sum("size") / F.count("*")).alias("n_over_k"),
        F.avg("radius").alias("mean_radius"),
        F.max("radius").alias("max_radius"),
        (F.sum(F.col("radius") * F.col("size")) / F.sum("size")).alias("weighted_radius"),
        F.sum("total").alias("total_distance"),
    )


def total_distance(assigned: DataFrame) -> DataFrame:
    return assigned.agg(F.sum("dist").alias("total_distance"))


def imbalance(members: DataFrame, key: str, workers: int) -> DataFrame:
    """One row: max over mean rows of a worker when rows are dealt by ``key``."""
    per = members.groupBy(F.pmod(F.xxhash64(key), F.lit(workers)).alias("w")).agg(F.count("*").alias("n"))
    return per.agg(F.max("n").alias("most"), (F.sum("n") / workers).alias("mean"), (F.max("n") * workers / F.sum("n")).alias("ratio"))


def exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan of ``df``."""
    return len(re.findall(r"\bExchange\b", df._jdf.queryExecution().executedPlan().toString()))


def exchanged(df: DataFrame) -> dict[str, int]:
    """Runs ``df``: exchanges of the plan that ran, and the rows and bytes they wrote."""
    plan = df._jdf.queryExecution()
    plan.toRdd().count()
    found, todo = {"exchanges": 0, "rows": 0, "bytes": 0}, [plan.executedPlan()]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
        elif name.endswith("QueryStageExec"):
            todo.append(node.plan())
        elif name != "ReusedExchangeExec":
            if name == "ShuffleExchangeExec":
                found["exchanges"] += 1
                for key, metric in (("rows", "shuffleRecordsWritten"), ("bytes", "shuffleBytesWritten")):
                    found[key] += node.metrics().apply(metric).value()
            children = node.children()
            todo += [children.apply(i) for i in range(children.size())]
    return found


def sample_share(k: int, n: int, per_center: int = 256) -> float:
    return per_center * k / n


def slope(points: DataFrame, y: str = "seconds", x: str = "k_star") -> DataFrame:
    return points.agg(F.regr_slope(F.col(y), F.col(x)).alias("slope"), F.regr_intercept(F.col(y), F.col(x)).alias("intercept"))


def scaling(points: DataFrame) -> DataFrame:
    """Speed-up T(1)/T(g) by workers from (workers, seconds, radius)."""
    one = points.filter("workers = 1").agg(F.avg("seconds").alias("one"), F.avg("radius").alias("r1"))
    return points.crossJoin(F.broadcast(one)).select("workers", "seconds", (F.col("one") / F.col("seconds")).alias("speedup"), (F.col("radius") / F.col("r1")).alias("radius_ratio"))


def collision_curve(pairs: DataFrame, dist: str, same: str, low: float, high: float, bands: int) -> DataFrame:
    """(band, pairs, rate): how often hashes collide by distance band."""
    return (
        pairs.withColumn("band", F.width_bucket(F.col(dist), F.lit(low), F.lit(high), F.lit(bands)).cast("int"))
        .groupBy("band")
        .agg(F.count("*").alias("pairs"), F.sum(F.col(same).cast("bigint")).alias("same"))
        .withColumn("rate", F.col("same") / F.col("pairs"))
    )


def group_overlap(a: DataFrame, b: DataFrame, theta: float = 0.5) -> DataFrame:
    """One row: groups of ``a``, and how many have a group of ``b`` with Jaccard >= theta."""
    na = a.groupBy("group_id").agg(F.count("*").alias("na"))
    nb = b.groupBy(F.col("group_id").alias("other")).agg(F.count("*").alias("nb"))
    both = (
        a.select("group_id", "id").join(b.select(F.col("group_id").alias("other"), "id"), "id")
        .groupBy("group_id", "other").agg(F.count("*").alias("c"))
    )
    twins = (
        both.join(na, "group_id").join(nb, "other")
        .filter(F.col("c") >= theta * (F.col("na") + F.col("nb") - F.col("c")))
        .select("group_id").distinct()
    )
    return na.agg(F.count("*").alias("groups")).crossJoin(twins.agg(F.count("*").alias("with_twin")))


def purity(assigned: DataFrame, truth: DataFrame, label: str = "truth") -> DataFrame:
    """One row: the share of rows whose label is their cluster's most frequent one."""
    counts = assigned.join(truth.select("id", label), "id").groupBy("cluster_id", label).agg(F.count("*").alias("n"))
    best = counts.groupBy("cluster_id").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return best.agg(F.sum("top").alias("top"), F.sum("n").alias("n"), (F.sum("top") / F.sum("n")).alias("purity"))


def pair_pr(assigned: DataFrame, truth: DataFrame, label: str = "truth") -> DataFrame:
    """One row: precision and recall over pairs, from counts alone."""
    rows = assigned.join(truth.select("id", label), "id")
    pairs = lambda keys: rows.groupBy(*keys).agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("p"))
    both, found, true = pairs(["cluster_id", label]), pairs(["cluster_id"]), pairs([label])
    return both.select(F.col("p").alias("both")).crossJoin(found.select(F.col("p").alias("found"))).crossJoin(true.select(F.col("p").alias("true"))).select(
        (F.col("both") / F.col("found")).alias("precision"), (F.col("both") / F.col("true")).alias("recall")
    )
