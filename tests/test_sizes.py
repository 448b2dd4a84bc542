"""Plans that hold at size: what is kept off the driver and off the disk, with the results it had before."""

import pytest
from pyspark.sql import functions as F

from bucketseed.experiments import surface
from bucketseed.functions.doph import doph
from bucketseed.functions.minhash import minhash_values
from bucketseed.functions.permutations import PRIME, draw
from bucketseed.operators import assign, metrics, nns, postings
from bucketseed.staging import staged
from tests.conftest import SF


def test_appended_rows_of_a_stream_are_read_from_files(spark):
    found = surface.session(spark, SF)
    assert found.inputFiles()
    assert found.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{SF}/events.parquet").count()


def _sets(spark, n=90, wide=7):
    token = lambda i: ((F.col("id") * (i + 3) + i * i) % F.lit(11 + i)).cast("bigint") * 16 + i
    rows = spark.range(n).select("id", F.array_distinct(F.array(*[token(i) for i in range(wide)])).alias("tokens"))
    bare = F.when(F.col("id") % 29 == 5, F.array().cast("array<bigint>")).otherwise(F.col("tokens"))
    return rows.withColumn("tokens", F.sort_array(bare))


def _jaccards(a, b):
    """{(i, j): jaccard} of all pairs, by Python's sets."""
    a, b = ({r[0]: set(r["tokens"]) for r in df.collect()} for df in (a, b))
    return {(i, j): 1.0 if not x | y else 1 - (1 - len(x & y) / len(x | y)) for i, x in a.items() for j, y in b.items()}


def test_lookups_exchange_only_each_tasks_nearest(spark, monkeypatch):
    rows = staged(_sets(spark).repartition(3), "rows")
    queries = rows.filter("id % 4 = 1").select(F.col("id").alias("qid"), "tokens")
    perms = draw(6, 4)
    hashes = {r["id"]: tuple(min(((t * a + b) % PRIME for t in r["tokens"]), default=-1) for a, b in perms.params) for r in rows.collect()}
    expected = {}
    for (q, i), s in _jaccards(queries, rows).items():
        if any(hashes[q][at : at + 2] == hashes[i][at : at + 2] for at in (0, 2, 4)):
            expected.setdefault(q, []).append((1 - s, i))
    expected = sorted((q, i, round(d, 12), n) for q, near in expected.items() for n, (d, i) in enumerate(sorted(near)[:3], 1))
    for size in (postings.CHUNK_TOKENS, 40):
        monkeypatch.setattr(postings, "CHUNK_TOKENS", size)
        found = nns.minhash_nns(rows, queries, 2, 3, 3, perms=perms)
        assert sorted((r["qid"], r["id"], round(r["dist"], 12), r["rank"]) for r in found.collect()) == expected
    # the base's sets are not exchanged: what moves is (qid, id, dist), three rows of a query and task at most
    assert metrics.exchanged(nns.minhash_nns(rows, queries, 2, 3, 3, perms=perms))["rows"] <= 3 * queries.count() * rows.rdd.getNumPartitions()


def test_similarity_join_loses_no_link_and_exchanges_nothing(spark, monkeypatch):
    rows = staged(_sets(spark), "rows")
    left = rows.filter("id % 4 = 1").select(F.col("id").alias("qid"), "tokens")
    expected = {pair for pair, s in _jaccards(left, rows).items() if s >= 0.2}
    for size, hits in ((postings.CHUNK_TOKENS, postings.HITS), (40, 30)):
        monkeypatch.setattr(postings, "CHUNK_TOKENS", size)
        monkeypatch.setattr(postings, "HITS", hits)
        assert {(r["qid"], r["id"]) for r in nns.similarity_join(left, rows, 0.2).collect()} == expected
    assert metrics.exchanged(nns.similarity_join(left, rows, 0.2))["exchanges"] == 0


@pytest.mark.parametrize("size", [postings.CHUNK_TOKENS, 40])
def test_exact_pairs_are_all_pairs_without_an_exchange(spark, monkeypatch, size):
    monkeypatch.setattr(postings, "CHUNK_TOKENS", size)
    rows = staged(_sets(spark).repartition(3), "rows")
    bare = {r["id"] for r in rows.collect() if not r["tokens"]}
    expected = {p: s for p, s in _jaccards(rows, rows).items() if p[0] < p[1] and s > 0 and not {*p} <= bare}
    for least in (0.0, 0.3, 0.5, 0.75, 1.0):
        found = {(r["a"], r["b"]): r["jaccard"] for r in nns.exact_pairs(rows, least).collect()}
        assert found == pytest.approx({p: s for p, s in expected.items() if s >= least - 1e-12})
    assert metrics.exchanged(nns.exact_pairs(rows, 0.5))["exchanges"] == 0


@pytest.mark.parametrize("hits", [postings.HITS, 50])
def test_bands_count_all_pairs_and_write_none(spark, monkeypatch, hits):
    monkeypatch.setattr(postings, "HITS", hits)
    perms = draw(3, 8)
    rows = staged(_sets(spark).repartition(3).select("id", "tokens", minhash_values("tokens", perms).alias("h")), "rows")
    h = {r["id"]: r["h"] for r in rows.collect()}
    expected = {}
    for pair in nns.exact_pairs(rows, 0.0).collect():
        at = expected.setdefault(min(int((1 - pair["jaccard"]) * 10), 9), [0, 0])
        at[0] += 1
        at[1] += sum(x == y for x, y in zip(h[pair["a"]], h[pair["b"]], strict=True))
    found = postings.band_counts(rows, 3)
    assert {r["band"]: [r["pairs"], r["same"]] for r in found.collect()} == expected
    assert metrics.exchanged(found)["rows"] <= 10 * rows.rdd.getNumPartitions()


def test_estimates_come_with_their_pairs(spark):
    rows = staged(_sets(spark), "rows")
    coords = {r["id"]: r["coords"] for r in doph(rows, dims=16, seed=3).collect()}
    found = postings.similar_pairs(doph(rows, dims=16, seed=3, keep=("tokens",)), 0.5)
    assert {(r["a"], r["b"]) for r in found.collect()} == {(r["a"], r["b"]) for r in nns.exact_pairs(rows, 0.5).collect()}
    for r in found.collect():
        assert r["estimate"] == sum(x == y for x, y in zip(coords[r["a"]], coords[r["b"]], strict=True)) / 16
    assert metrics.exchanged(found)["exchanges"] == 0


@pytest.mark.parametrize("size", [assign.CENTER_BYTES, 100])
def test_matches_are_counted_without_an_exchange(spark, monkeypatch, size):
    monkeypatch.setattr(assign, "CENTER_BYTES", size)
    cells = lambda i: F.array(*[((F.col("id") * (j + i) + j) % (3 + j)).cast("bigint") for j in range(5)])
    rows = staged(spark.range(60).select("id", cells(2).alias("tokens")), "rows")
    centers = staged(spark.range(9).select((F.col("id") * 2 + 1).alias("seed_id"), (cells(7) if size > 100 else cells(3)).alias("modes")), "centers")
    c = [(r["seed_id"], r["modes"]) for r in centers.collect()]
    found = assign.assign(rows, centers, strategy="match", vec="tokens", center="modes")
    got = {r["id"]: (r["cluster_id"], r["dist"]) for r in found.collect()}
    for r in rows.collect():
        m, seed = max((sum(x == y for x, y in zip(r["tokens"], v, strict=True)), -s) for s, v in c)
        assert got[r["id"]] == (-seed, 1 - m / (10 - m))
    if size > 100:
        assert metrics.exchanged(found)["exchanges"] == 0
