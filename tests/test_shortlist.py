"""The shortlist over broadcast centers: the candidates' nearest, the full scan for the rest, and nothing moves."""

import pytest
from pyspark.sql import functions as F

from bucketseed.functions.permutations import PRIME, draw
from bucketseed.operators import assign, metrics
from bucketseed.staging import staged


@pytest.mark.parametrize("size", [assign.CENTER_BYTES, 1200])
def test_shortlist_moves_neither_signatures_nor_candidates(spark, monkeypatch, size):
    monkeypatch.setattr(assign, "CENTER_BYTES", size)
    monkeypatch.setattr(assign, "PAIR_CELLS", 40)
    cells = F.array(*[(F.pmod(F.xxhash64("id", F.lit(j)), F.lit(2 + j)) * 16 + j).cast("bigint") for j in range(6)])
    rows = staged(spark.range(120).select("id", cells.alias("tokens")), "rows")
    seeds = staged(rows.filter("id % 9 = 2").select((F.col("id") + 1000).alias("seed_id"), F.col("tokens").alias("modes")), "seeds")
    perms = draw(20, 5)
    hashes = lambda t: [min((v * a + b) % PRIME for v in t) for a, b in perms.params]
    c = [(r["seed_id"], r["modes"], hashes(r["modes"])) for r in seeds.collect()]
    found = assign.assign(rows, seeds, strategy="shortlist", vec="tokens", center="modes")
    got = {r["id"]: (r["cluster_id"], r["dist"]) for r in found.collect()}
    scans = 0
    for r in rows.collect():
        h = hashes(r["tokens"])
        near = [(i, t) for i, t, g in c if any(h[at : at + 2] == g[at : at + 2] for at in range(0, 20, 2))]
        scans += not near
        m, seed = max((sum(x == y for x, y in zip(r["tokens"], t, strict=True)), -i) for i, t in near or [(i, t) for i, t, _ in c])
        assert got[r["id"]] == (-seed, 1 - m / (12 - m))
    assert 0 < scans < len(got) == 120
    if size > 1200:
        assert metrics.exchanged(found)["exchanges"] == 0
