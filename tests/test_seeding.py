"""The worked example of six objects, and properties of the vote."""

import pytest
from pyspark.sql import functions as F

from bucketseed.functions.permutations import draw
from bucketseed.operators import baselines, metrics, seeding
from bucketseed.operators.assign import assign, k_star
from bucketseed.operators.centers import centroids, numbered
from bucketseed.operators.ranking import ranked
from bucketseed.staging import staged, staged_by

BUCKETS = {
    "B1": [1, 2, 4], "B2": [3, 5, 6], "B3": [1, 2, 3, 4, 5], "B4": [6],
    "B5": [1, 2, 4, 6], "B6": [3, 5], "B7": [1, 2, 4], "B8": [3, 5, 6],
}


def members(spark):
    return spark.createDataFrame([(b, i) for b, ids in BUCKETS.items() for i in ids], "bucket_id string, id bigint")


def bins(spark, given):
    rows = [(f"{n}", 0, b, len(bs)) for n, bs in given.items() for b in bs if len(bs) >= 2]
    return spark.createDataFrame(rows, "bin_id string, bin_table int, bucket_id string, bin_size bigint")


def groups_of(df):
    out = {}
    for r in df.collect():
        out.setdefault(r["group_id"], set()).add(r["id"])
    return {tuple(sorted(v)) for v in out.values()}


@pytest.mark.parametrize(
    "given, expected",
    [
        ({"a": ["B1", "B3", "B5", "B7"], "b": ["B2", "B6", "B8"], "c": ["B4"]}, {(1, 2, 4), (3, 5, 6)}),
        ({"a": ["B1", "B3", "B5", "B7"], "b": ["B2", "B4"], "c": ["B6", "B8"]}, {(1, 2, 4), (6,), (3, 5)}),
        ({"a": ["B1", "B3"], "b": ["B2", "B4"]}, {(1, 2, 4), (6,)}),
        ({"a": ["B5", "B7"], "b": ["B6", "B8"]}, {(1, 2, 4), (3, 5)}),
    ],
)
def test_votes_of_the_example(spark, given, expected):
    assert groups_of(seeding.majority_vote(bins(spark, given), members(spark))) == expected


def test_two_buckets_need_both_and_half_of_four_is_not_enough(spark):
    m = spark.createDataFrame([(b, i) for b, ids in {"a": [1, 2], "b": [1], "c": [1, 2], "d": [1]}.items() for i in ids], "bucket_id string, id bigint")
    four = bins(spark, {"x": ["a", "b", "c", "d"]})
    assert groups_of(seeding.majority_vote(four, m)) == {(1,)}
    assert groups_of(seeding.majority_vote(bins(spark, {"x": ["a", "b"]}), m)) == {(1,)}


def test_dedup_keeps_singletons_and_merges_equal_groups(spark):
    rows = [("g1", i) for i in (1, 2, 4)] + [("g2", i) for i in (1, 2, 4)] + [("g3", 6)]
    groups = spark.createDataFrame(rows, "group_id string, id bigint")
    assert groups_of(seeding.dedup_groups(groups, 2)) == {(1, 2, 4), (6,)}
    assert groups_of(seeding.dedup_groups(groups, 2, singletons="drop")) == {(1, 2, 4)}
    assert groups_of(seeding.collapse_equal(groups)) == {(1, 2, 4), (6,)}


def test_every_shared_bin_has_a_core_and_pruning_changes_nothing(spark):
    m = spark.range(400).select(
        F.explode(F.sequence(F.lit(0), F.lit(5))).alias("table_id"), "id"
    ).withColumn("bucket_id", F.concat_ws(":", "table_id", (F.col("id") / (10 + F.col("table_id"))).cast("int")))
    perms = draw(8, 3)
    sigs = seeding.bucket_signatures(m, perms)
    shared = seeding.make_bins(sigs, 2, 4, prune=False)
    voted = seeding.majority_vote(shared, m)
    assert shared.select("bin_id").distinct().count() == voted.select("group_id").distinct().count()
    a = seeding.seed_round(m, 2, 4, 5, perms, prune=True).select("group_id", "id").collect()
    b = seeding.seed_round(m.repartition(7), 2, 4, 5, perms, prune=False).select("group_id", "id").collect()
    assert sorted(a) == sorted(b)


def test_batches_equal_local_parts(spark):
    m = spark.range(300).select(F.explode(F.sequence(F.lit(0), F.lit(3))).alias("table_id"), "id").withColumn(
        "bucket_id", F.concat_ws(":", "table_id", (F.col("id") / 20).cast("int"))
    )
    ids = lambda df: sorted(groups_of(df))
    local = seeding.similar_bucket_seeds(m, 2, 4, 2, vote="local", parts=2)
    assert ids(local) == ids(seeding.similar_bucket_seeds(m, 2, 4, 2, batches=2))


def test_empty_members(spark):
    empty = spark.createDataFrame([], "bucket_id string, table_id int, id bigint")
    assert seeding.similar_bucket_seeds(empty, 2, 4, 2).count() == 0


def test_local_voting_exchanges_once(spark):
    rows = spark.range(300).select((F.col("id") % 60).alias("id"), F.concat(F.lit("b"), (F.col("id") % 40).cast("string")).alias("bucket_id"), (F.col("id") % 6).cast("int").alias("table_id"))
    members = staged(rows.distinct(), "members")
    perms = draw(8, 0)
    with seeding.colocated(spark):
        local = metrics.exchanged(seeding.local_round(members, 2, 4, 1, perms, 3))
    whole = metrics.exchanged(seeding.seed_round(members, 2, 4, 1, perms))
    assert local["exchanges"] == 1 and local["rows"] == members.count()
    assert whole["exchanges"] > 1 and whole["rows"] > local["rows"]
    assert spark.conf.get("spark.sql.requireAllClusterKeysForCoPartition") == "true"


def test_a_batch_reads_its_own_members(spark):
    split = staged_by(spark.range(100).withColumn("_batch", (F.col("id") % 4).cast("int")), "_batch", "batches")
    plan = split.filter("_batch = 1")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(_batch" in plan and split.filter("_batch = 1").count() == 25


def test_ranks_are_those_of_one_sort(spark):
    rows = spark.range(500).select("id", (F.col("id") % 3).alias("g"), F.when(F.col("id") % 11 > 0, F.col("id") % 7).alias("h"))
    got, given = ranked(rows, ["h", "id"], ["id"], ["g"]).collect(), rows.collect()
    for g in range(3):
        order = sorted((r["h"] is not None, r["h"] or 0, r["id"]) for r in given if r["g"] == g)
        assert [r["id"] for r in sorted((r for r in got if r["g"] == g), key=lambda r: r["rank"])] == [x[2] for x in order]
        assert {r["total"] for r in got if r["g"] == g} == {len(order)}
    assert ranked(rows.filter("id < 0"), ["id"], ["id"]).count() == 0


def test_work_is_counted_in_row_center_distances(spark):
    data = spark.range(40).select("id", F.array((F.col("id") % 4).cast("double"), (F.col("id") % 2).cast("double")).alias("vec"))
    fit = baselines.lloyd(data, 3, max_iter=2, tol=-1.0)
    assert fit.iterations == 2 and not fit.converged and 40 * 3 >= fit.evaluations / 3 > 40
    tokens = spark.range(30).select("id", F.array((F.col("id") % 3).cast("bigint"), (F.col("id") % 5).cast("bigint")).alias("tokens"))
    moded = baselines.kmodes(tokens, 3, max_iter=50)
    assert moded.converged and moded.evaluations % 30 == 0 and moded.evaluations >= 30 * 3 * 2 - 30 * 3
    near = {r["id"]: r["cluster_id"] for r in moded.assigned.collect()}
    assert len(near) == 30 and len(set(near.values())) <= 3


def test_more_seeds_tell_the_small_cluster_apart(spark):
    # the example's six objects on a line: one table's groups absorb object 6, both tables' groups don't
    data = spark.createDataFrame([(1, [0]), (2, [10]), (4, [20]), (3, [1000]), (5, [1010]), (6, [1600])], "id bigint, vec array<bigint>")

    def clusters(groups):
        rows = [(str(n), i) for n, ids in enumerate(groups) for i in ids]
        seeds = numbered(spark.createDataFrame(rows, "group_id string, id bigint"))
        found = assign(data, centroids(seeds, data), strategy="sql")
        out = {}
        for r in found.collect():
            out.setdefault(r["cluster_id"], set()).add(r["id"])
        return found, {tuple(sorted(v)) for v in out.values()}

    first = [(1, 2, 4), (3, 5, 6)]
    one, got = clusters(first)
    assert got == {(1, 2, 4), (3, 5, 6)}
    both, got = clusters(first + [(6,), (3, 5)])
    assert got == {(1, 2, 4), (3, 5), (6,)} and k_star(both).first()[0] == 3
    assert metrics.radius_summary(both).first()["max_radius"] < metrics.radius_summary(one).first()["max_radius"]
