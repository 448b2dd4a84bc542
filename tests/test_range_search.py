"""Range search over broadcast queries: all rows within reach, and no pair moves."""

import pytest
from pyspark.sql import functions as F

from bucketseed.operators import assign, metrics, micro
from bucketseed.staging import staged


@pytest.mark.parametrize(("cells", "distances"), [(micro.CHUNK_CELLS, micro.DISTANCES), (40, 50)])
def test_range_search_finds_all_without_moving_pairs(spark, monkeypatch, cells, distances):
    monkeypatch.setattr(micro, "CHUNK_CELLS", cells)
    monkeypatch.setattr(micro, "DISTANCES", distances)
    vec = F.array(*[F.pmod(F.xxhash64("id", F.lit(j)), F.lit(1000)) * 1000 for j in range(4)])
    rows = staged(spark.range(200).select("id", vec.alias("vec")), "rows")
    centers = staged(rows.filter("id % 20 = 0").select(F.col("id").alias("seed_id"), "vec"), "centers")
    assigned = staged(assign.assign(rows, centers), "assigned")
    clusters = centers.withColumnRenamed("seed_id", "cluster_id").join(metrics.radii(assigned).select("cluster_id", "radius"), "cluster_id")
    queries = rows.filter("id % 9 = 4").select(F.col("id").alias("qid"), "vec")
    x = {r["id"]: r["vec"] for r in rows.collect()}
    expected = {}
    for q in (r["qid"] for r in queries.collect()):
        for i, v in x.items():
            d = sum(float((a - b) ** 2) for a, b in zip(x[q], v, strict=True)) ** 0.5
            if d <= 400_000:
                expected[q, i] = d
    found = micro.range_search(clusters, assigned, rows, queries, 400_000)
    assert {(r["qid"], r["id"]): r["dist"] for r in found.collect()} == expected
    if cells > 40:
        # the assignment and the vectors meet; clusters' queries don't
        assert metrics.exchanged(found)["rows"] <= 2 * rows.count()
