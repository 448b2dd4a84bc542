import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketseed.functions import features as ft
from bucketseed.functions.distances import Matches
from bucketseed.functions.doph import doph, doph_column
from bucketseed.functions.families import FAMILIES, suggest_params
from bucketseed.operators import assign as asg
from bucketseed.operators import baselines, metrics
from bucketseed.operators import transform as tf
from bucketseed.operators.centers import centroids, modes
from bucketseed.plans import threephase
from bucketseed.plans.estimator import BucketSeedClusterer, BucketSeedModel
from bucketseed.sources.planted import planted_gauss, planted_mixed, planted_sets, register_data_source
from bucketseed.sources.readers import read_sparse_text


@pytest.fixture(scope="module")
def gauss(spark):
    return planted_gauss(spark, 600, 12, 8, 0.02).cache()


def test_rank_cuts_agree_and_are_even(spark, gauss):
    a = tf.transform_dense(gauss, "vec", 5, 7).collect()
    b = tf.transform_dense(gauss.repartition(5), "vec", 5, 7, mode="ranked").collect()
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))
    sizes = tf.transform_dense(gauss, "vec", 3, 7).groupBy("bucket_id").count().collect()
    assert {r["count"] for r in sizes} <= {85, 86}


def test_discretising_modes_agree(spark):
    rows = spark.range(500).select("id", (F.col("id") * 37 % 101).cast("double").alias("x"), (F.col("id") * 11 % 7).cast("double").alias("y"))
    a, b = (sorted(map(tuple, tf.discretise(rows, ["x", "y"], 6, mode=m).collect())) for m in ("window", "ranked"))
    assert a == b


def test_rank_cut_of_six_on_a_line(spark):
    rows = spark.createDataFrame([(0, i, i * 10) for i in range(6)], "table_id int, id bigint, h bigint")
    for mode in ("window", "ranked"):
        two = sorted(r["count"] for r in tf.rank_cut(rows, 2, mode).groupBy("bucket_id").count().collect())
        four = sorted(r["count"] for r in tf.rank_cut(rows, 4, mode).groupBy("bucket_id").count().collect())
        assert (two, four) == ([3, 3], [1, 1, 2, 2])
        assert tf.rank_cut(rows, 50, mode).select("bucket_id").distinct().count() == 6


def test_densified_forms_agree(spark):
    sets = spark.createDataFrame([(1, [5, 9, 1 << 20]), (2, []), (3, list(range(1, 300, 7))), (4, [77])], "id bigint, tokens array<bigint>")
    a = {r["id"]: r["coords"] for r in doph(sets, dims=16, seed=4).collect()}
    b = {r["id"]: r["c"] for r in sets.select("id", doph_column("tokens", 16, 4).alias("c")).collect()}
    assert a == b and a[2] == [-1] * 16 and len(set(a[4])) == 1
    c = {r["id"]: r["coords"] for r in doph(sets, dims=16, seed=4, densify="optimal").collect()}
    assert set(c[3]) == set(a[3])


def test_match_rate_of_coordinates_estimates_similarity(spark):
    rng = np.random.default_rng(0)
    base = rng.choice(1 << 27, 400, replace=False)
    other = np.concatenate([base[:320], rng.choice(1 << 27, 80, replace=False)])
    rows = spark.createDataFrame([(1, base.tolist()), (2, other.tolist())], "id bigint, tokens array<bigint>")
    got = {r["id"]: np.array(r["coords"]) for r in doph(rows, dims=400).collect()}
    true = 320 / 480
    assert abs((got[1] == got[2]).mean() - true) < 3 * (true * (1 - true) / 400) ** 0.5


def test_assignment_strategies_agree(spark, gauss):
    centers = baselines.random_seeds(gauss, 9)
    a = {r["id"]: r["cluster_id"] for r in asg.assign(gauss, centers, strategy="sql").collect()}
    b = {r["id"]: r["cluster_id"] for r in asg.assign(gauss, centers).collect()}
    assert a == b
    ids, c = asg.collected(centers, "vec")
    chunked = asg._assign_chunks(gauss, ids, c, "euclidean", "vec", 4)
    assert {r["id"]: r["cluster_id"] for r in chunked.collect()} == a


def test_match_equals_blocks(spark):
    rows = spark.range(60).select("id", F.array(*[(F.col("id") * (i + 3) % (i + 4)).cast("bigint") for i in range(6)]).alias("tokens"))
    centers = rows.filter("id < 7").select(F.col("id").alias("seed_id"), F.col("tokens").alias("modes"))
    a = asg.assign(rows, centers, strategy="match", vec="tokens", center="modes").collect()
    b = asg.assign(rows, centers, "jaccard_tokens", "gemm", "tokens", "modes").collect()
    key = lambda rs: sorted((r["id"], r["cluster_id"], round(r["dist"], 9)) for r in rs)
    assert key(a) == key(b)


def test_matches_count_equal_coordinates():
    draw = np.random.default_rng(3)
    x, c = draw.integers(0, 6, (50, 300)), draw.integers(2, 9, (40, 300))
    assert (Matches(c).count(x) == (x[:, None] == c[None]).sum(-1)).all()
    assert Matches(c).count(x[:0]).shape == (0, 40)


def test_kmodes_is_the_plain_loop(spark):
    """Keeping the modes of clusters without a change gives what recomputing all of them gives."""
    table = np.random.default_rng(5).integers(0, 3, (60, 5))
    rows = spark.createDataFrame([(i, [int(v) for v in r]) for i, r in enumerate(table)], "id bigint, tokens array<bigint>")
    init = spark.createDataFrame([(s, [int(v) for v in table[7 * s]]) for s in range(6)], "seed_id bigint, modes array<bigint>")
    names, centers = np.arange(6), table[[7 * s for s in range(6)]]

    def nearest():
        m = (table[:, None] == centers[None]).sum(-1)
        return names[m.argmax(1)]

    now, before, turns = nearest(), None, 0
    while turns < 50 and (before is None or (now != before).any()):
        before, names = now, np.unique(now)
        centers = np.array([[np.bincount(col).argmax() for col in table[before == s].T] for s in names])
        now, turns = nearest(), turns + 1
    got = baselines.kmodes(rows, init=init, max_iter=50)
    assert {r["id"]: r["cluster_id"] for r in got.assigned.collect()} == dict(enumerate(now.tolist()))
    assert got.iterations == turns > 2 and got.converged and (got.centers == centers).all()


def test_centers(spark):
    data = spark.createDataFrame([(1, [0, 10]), (2, [1, 10]), (3, [1, 20])], "id bigint, vec array<bigint>")
    groups = spark.createDataFrame([(1, 1), (1, 2), (1, 3)], "seed_id bigint, id bigint")
    assert centroids(groups, data).first()["vec"] == [1, 13]
    assert modes(groups, data.withColumnRenamed("vec", "tokens")).first()["modes"] == [1, 10]


def test_yinyang_is_lloyd_with_fewer_distances(spark, gauss):
    init = baselines.random_seeds(gauss, 30).cache()
    a, b = baselines.lloyd(gauss, init=init), baselines.yinyang(gauss, init=init)
    assert {r["id"]: r["cluster_id"] for r in a.assigned.collect()} == {r["id"]: r["cluster_id"] for r in b.assigned.collect()}
    assert b.evaluations < a.evaluations
    assert all(x >= y - 1e-3 for x, y in zip(a.objective, a.objective[1:], strict=False))


def test_baselines_keep_their_counts(spark, gauss):
    s = baselines.sampled_kmeans(gauss, 15, 8)
    assert asg.k_star(s.assigned).first()[0] <= 15
    assert baselines.kmeanspp_seeds(gauss, 5).count() == 5
    assert baselines.kmeans_parallel_seeds(gauss, 5).count() == 5
    assert baselines.random_seeds(gauss, 1000).count() == 600


@pytest.mark.parametrize("kind", ["dense", "sparse", "hetero"])
def test_planted_clusters_come_back(spark, gauss, kind):
    if kind == "dense":
        truth, run = gauss, threephase.cluster_dense(gauss.select("id", "vec"), m=30, t=12, K=2, L=10, delta=5)
    elif kind == "sparse":
        truth = planted_sets(spark, 400, 16)
        run = threephase.cluster_sparse(truth.select("id", "tokens"), D=64, K=2, L=8, delta=3)
    else:
        truth = planted_mixed(spark, 500, 10)
        run = threephase.cluster_hetero(truth, ["x", "y"], ["a", "b", "c"], K_t=2, L_t=15, bins=10, K=2, L=8, delta=3)
    assert metrics.purity(run.assigned, truth).first()["purity"] > 0.9


def test_estimator_round_trip(spark, gauss, tmp_path):
    est = BucketSeedClusterer(tf.DatasetSpec("dense", "id", "vec"), m=20, t=12, K=2, L=8, delta=5)
    model = est.fit(gauss)
    model.save(str(tmp_path / "m"))
    again = BucketSeedModel.load(spark, str(tmp_path / "m"))
    a = sorted(map(tuple, model.transform(gauss).collect()))
    assert a == sorted(map(tuple, again.transform(gauss).collect()))


def test_families_collide_less_with_distance():
    for name, cls in FAMILIES.items():
        family = cls(dims=16, width=4.0)
        family.draw(3, 0)
        near, far = (0.1, 0.8) if name in ("jaccard", "cosine") else (1.0, 6.0)
        assert family.p(near) > family.p(far), name
    assert suggest_params(10**6, 0.9, 0.5)["L"] >= 1


def test_features_on_edges(spark, tmp_path):
    rows = spark.createDataFrame([(1, None), (2, ""), (3, "a a b"), (4, "abc")], "id bigint, text string")
    sets = {r["id"]: r["t"] for r in rows.select("id", ft.word_set("text").alias("t")).collect()}
    assert sets[1] == [] and sets[2] == [] and len(sets[3]) == 2
    grams = {r["id"]: len(r["t"]) for r in rows.select("id", ft.shingle_set("text", 5).alias("t")).collect()}
    assert grams == {1: 1, 2: 1, 3: 1, 4: 1}
    good, bad = ft.validate(spark.createDataFrame([(1.0,), (None,), (float("nan"),)], "x double"), ["x"])
    assert (good.count(), bad.count()) == (1, 2)
    (tmp_path / "s.txt").write_text("7 3:1.5 1:2 junk\n\n8\n")
    got = {r["id"]: r["tokens"] for r in read_sparse_text(spark, str(tmp_path / "s.txt")).collect()}
    assert got == {7: [1, 3], 8: []}


def test_planted_source(spark):
    register_data_source(spark)
    assert spark.read.format("planted").option("rows", "50").load().count() == 50
