"""k-modes at size: only what moved is compared, and rows move whole."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketseed.operators import assign, baselines, centers, metrics
from bucketseed.staging import staged


def _plain_kmodes(x, ids, c, turns):
    """Every row against every center, by Python's counts."""
    for turn in range(turns + 1):
        who = [max(range(len(c)), key=lambda j: (sum(a == b for a, b in zip(r, c[j], strict=True)), -ids[j])) for r in x]
        if turn == turns:
            return [ids[j] for j in who], c
        groups = {j: [r for r, w in zip(x, who, strict=True) if w == j] for j in sorted(set(who))}
        ids, c = [ids[j] for j in groups], [[max(sorted(set(v)), key=v.count) for v in zip(*g, strict=True)] for g in groups.values()]


@pytest.mark.parametrize(("wide", "large"), [(3, centers.GROUP_ROWS), (3, 4), (5000, centers.GROUP_ROWS)])
def test_kmodes_compares_only_what_moved(spark, monkeypatch, wide, large):
    monkeypatch.setattr(centers, "GROUP_ROWS", large)
    cells = F.array(*[(F.xxhash64("id", F.lit(j)) % wide + wide).cast("bigint") for j in range(8)])
    rows = staged(spark.range(150).select("id", cells.alias("tokens")), "rows")
    init = staged(rows.filter("id % 7 = 3").select(F.col("id").alias("seed_id"), F.col("tokens").alias("modes")), "init")
    x, c = ([r["tokens"] for r in df.collect()] for df in (rows.orderBy("id"), init.orderBy("seed_id").withColumnRenamed("modes", "tokens")))
    who, modes = _plain_kmodes(x, [r[0] for r in init.orderBy("seed_id").collect()], c, 4)
    found = baselines.kmodes(rows, init=init, max_iter=4)
    assert [r["cluster_id"] for r in found.assigned.orderBy("id").collect()] == who
    assert found.centers.tolist() == modes
    assert found.evaluations < 150 * len(c) * (found.iterations + 1)


def test_modes_are_not_counted_value_by_value(spark):
    rows = staged(spark.range(60).select("id", F.array(*[(F.col("id") * (j + 3)) % 5 for j in range(40)]).alias("tokens")), "rows")
    groups = staged(rows.select((F.col("id") % 20).alias("seed_id"), "id"), "groups")
    assert metrics.exchanged(centers.modes(groups, rows))["rows"] <= 4 * 60


def test_centers_with_many_hits_are_counted_not_compared(monkeypatch):
    """Frequent values gave more hits than an index was used for."""
    monkeypatch.setattr(assign, "Matches", None)
    draw = np.random.default_rng(3)
    c, x = (draw.integers(0, 40, (n, 32)) for n in (2_500, 40))
    c[9], x[3], x[4], x[5] = c[7], c[9], -1, 1 << 60
    m, who = assign.Lookup(c).best(x)
    same = (x[:, None] == c[None]).sum(-1)
    assert (m == same.max(1)).all() and (who == same.argmax(1)).all() and who[3] == 7 and m[5] == 0


def test_seeded_rows_are_looked_up(spark, monkeypatch):
    looked_up, reassign = [], assign.reassign
    monkeypatch.setattr(assign, "reassign", lambda *a: looked_up.append(1) or reassign(*a))
    cells = F.array(*[(F.xxhash64("id", F.lit(j)) % 50).cast("bigint") for j in range(8)])
    rows = staged(spark.range(200).select("id", cells.alias("tokens")), "rows")
    init = staged(rows.filter("id % 5 = 3").select(F.col("id").alias("seed_id"), F.col("tokens").alias("modes")), "init")
    found = {s: sorted(map(tuple, assign.assign(rows, init, "jaccard_tokens", s, "tokens", "modes").collect())) for s in ("gemm", "match")}
    assert looked_up and found["gemm"] == found["match"]


def test_centers_beyond_an_index_come_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(assign, "INDEX_BYTES", 800)
    blocks, looked_up = [], assign.reassign
    monkeypatch.setattr(assign, "reassign", lambda rows, ids, *a: blocks.append(len(ids)) or looked_up(rows, ids, *a))
    cells = F.array(*[(F.xxhash64("id", F.lit(j)) % 9).cast("bigint") for j in range(8)])
    rows = staged(spark.range(120).select("id", cells.alias("tokens")), "rows")
    init = staged(rows.filter("id % 5 = 3").select(F.col("id").alias("seed_id"), F.col("tokens").alias("modes")), "init")
    found = {s: sorted(map(tuple, assign.assign(rows, init, "jaccard_tokens", s, "tokens", "modes").collect())) for s in ("gemm", "match")}
    assert blocks == [12, 12] and found["gemm"] == found["match"]
