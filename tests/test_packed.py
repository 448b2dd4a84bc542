"""Dense seeding where rows are read: the long tables' results, and few bytes of stage files."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketseed.operators import baselines, packed
from bucketseed.plans import threephase
from bucketseed.staging import shared_dir, staged


def _rows(spark, n, kind):
    h = lambda j, n: (F.xxhash64("id", F.lit(j)) % n).cast("bigint")
    if kind == "blobs":
        vec = F.array(*[(F.col("id") % 7 * (j + 3) % 5) * 100_000 + h(j, 9_000) for j in range(3)])
    elif kind == "ties":
        vec = F.array(*[h(j, 2) for j in range(3)])
    else:
        vec = F.array(F.lit(5), F.lit(5), F.lit(0)).cast("array<bigint>")
    return staged(spark.range(n).select(F.col("id") * 3, vec).toDF("id", "vec"), "rows")


def _written(spark, name):
    root = Path(shared_dir(spark).removeprefix("file:")) / "bucketseed"
    return {p.name: sum(f.stat().st_size for f in p.rglob("*.parquet")) for p in root.glob(f"{name}*")}


@pytest.mark.parametrize("collected", [20, packed.COLLECTED])
@pytest.mark.parametrize("kind", ["blobs", "ties", "equal"])
def test_packed_seeding_is_that_of_the_long_tables(spark, monkeypatch, kind, collected):
    monkeypatch.setattr(packed, "COLLECTED", collected)
    rows = _rows(spark, 3_000, kind)
    runs = []
    for small in (10_000, 100):
        monkeypatch.setattr(threephase, "SMALL_ROWS", small)
        run = threephase.cluster_dense(rows, m=8, t=7, K=2, L=4, delta=3)
        runs.append([sorted(map(tuple, df.select(sorted(df.columns)).collect())) for df in (run.members, run.groups, run.centers, run.assigned)])
    assert runs[0][1] and runs[0] == runs[1]


def test_large_tables_write_no_projections(spark, monkeypatch):
    """Members alone took 20 entries a row."""
    monkeypatch.setattr(threephase, "SMALL_ROWS", 100)
    rows, before = _rows(spark, 20_000, "blobs"), set(_written(spark, ""))
    threephase.cluster_dense(rows, m=20, t=10, K=2, L=4, delta=3)
    assert sum(size for name, size in _written(spark, "").items() if name not in before) < 20 * 20_000


def test_bounds_of_a_round_go_with_the_next(spark):
    rows = _rows(spark, 2_000, "blobs")
    before = set(_written(spark, "bounds"))
    init = staged(baselines.random_seeds(rows, 30), "init")
    a, b = baselines.lloyd(rows, init=init), baselines.yinyang(rows, init=init)
    assert b.iterations > 2 and len(set(_written(spark, "bounds")) - before) <= 1
    assert sorted(map(tuple, a.assigned.collect())) == sorted(map(tuple, b.assigned.collect()))
    assert np.array_equal(a.centers, b.centers)
