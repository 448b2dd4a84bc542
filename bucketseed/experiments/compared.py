"""The compared methods and the experiment workloads on the given tables.

A workload returns one row per method and setting: k*, rows per cluster, radii, total distance and
seconds. The rivals' k is the k* that the seeded run found, as k is their input.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.experiments import data, sql
from bucketseed.experiments.phases import EMB, EMB_T, embedding_assigned, embedding_centers
from bucketseed.functions.doph import doph
from bucketseed.functions.permutations import draw
from bucketseed.operators import assign as asg
from bucketseed.operators import baselines, metrics, micro, seeding
from bucketseed.operators import transform as tf
from bucketseed.plans import threephase
from bucketseed.plans.grid import best_by_band, combinations, grid_search
from bucketseed.sources.planted import planted_gauss, planted_mixed, planted_sets
from bucketseed.staging import staged

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


# ---- baselines --------------------------------------------------------------------------------

ONE = draw(1, 77)
_INIT = {"centers": f"SELECT id AS seed_id, vec FROM data ORDER BY {ONE.sql('id', 0)}, id LIMIT 20"}


@query("l_random", sql.with_(sql.embedding_rows() | _INIT, "SELECT seed_id, array_to_string(vec, ',') AS vec FROM centers"))
def random_seeds(spark, d):
    seeds = baselines.random_seeds(data.embedding_rows(spark, d), 20, perms=ONE)
    return seeds.select("seed_id", F.concat_ws(",", F.col("vec").cast("array<string>")).alias("vec"))


def _steps(n):
    ctes = sql.embedding_rows() | _INIT | sql.assign_dense("a0")
    for i in range(1, n + 1):
        ctes |= {f"g{i}": f"SELECT id, cluster_id AS seed_id FROM a{i - 1}"} | sql.centroids(f"g{i}", f"c{i}") | sql.assign_dense(f"a{i}", f"c{i}")
    return ctes


@query("l_lloyd_3", sql.with_(_steps(3), "SELECT id, cluster_id, round(dist, 3) AS dist FROM a3"))
def lloyd_three(spark, d):
    """Three updates on fixed-point vectors, so that every engine gets the same clusters."""
    rows = staged(data.embedding_rows(spark, d), "rows")
    init = staged(baselines.random_seeds(rows, 20, perms=ONE), "init")
    out = baselines.lloyd(rows, init=init, max_iter=3, tol=-1.0, exact=True).assigned
    return out.select("id", "cluster_id", F.round("dist", 3).alias("dist"))


_KM = sql.docs_sets() | sql.doph_coords(64, 0) | sql.COORD_SETS
_KM |= {"k0": f"SELECT id AS seed_id, tokens AS modes FROM csets ORDER BY {ONE.sql('id', 0)}, id LIMIT 20"}
_KM |= sql.assign_match("m0", centers="k0") | {"mg": "SELECT id, cluster_id AS seed_id FROM m0"} | sql.modes("mg", out="k1") | sql.assign_match("m1", centers="k1")


@query("l_kmodes_2", sql.with_(_KM, "SELECT id, cluster_id, round(dist, 6) AS dist FROM m1"))
def kmodes_two(spark, d):
    rows = _coords(data.docs_sets(spark, d), 64)
    init = baselines.random_seeds(rows, 20, vec="tokens", perms=ONE).select("seed_id", F.col("vec").alias("modes"))
    out = baselines.kmodes(rows, init=staged(init, "init"), max_iter=1).assigned
    return out.select("id", "cluster_id", F.round("dist", 6).alias("dist"))


def _coords(sets: DataFrame, D: int) -> DataFrame:
    return staged(doph(sets, dims=D).select("id", tf.coordinate_tokens("coords").alias("tokens")), "coords")


def _row(method: str, setting: str, assigned: DataFrame, seconds: float) -> DataFrame:
    named = metrics.radius_summary(assigned)
    return named.select(F.lit(method).alias("method"), F.lit(setting).alias("setting"), *named.columns, F.lit(seconds).alias("seconds"))


def _union(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def _fitted(method: str, setting: str, fit) -> DataFrame:
    """The assignment is summed up where it is made; no row of it is written."""
    began = time.perf_counter()
    found = fit()
    fitted = found if isinstance(found, baselines.Fitted) else None
    row = _row(method, setting, fitted.assigned if fitted else found, 0.0)
    got = row.first().asDict() | {"seconds": time.perf_counter() - began}
    return row.sparkSession.createDataFrame([tuple(got.values())], row.schema).withColumns(
        {
            "evaluations": F.lit(int(fitted.evaluations if fitted else 0)),
            "iterations": F.lit(fitted.iterations if fitted else 0),
            "converged": F.lit(fitted.converged if fitted else True),
        }
    )


@query("l_lloyd")
def lloyd(spark, d):
    return _fitted("lloyd", "k=20", lambda: baselines.lloyd(data.letter_rows(spark, d), 20))


@query("l_yinyang")
def yinyang(spark, d):
    """Lloyd and the grouped-bound variant from the same seeds: equal figures, fewer distances."""
    rows = staged(data.letter_rows(spark, d), "rows")
    init = staged(baselines.random_seeds(rows, 30), "init")
    return _union(
        [
            _fitted("lloyd", "k=30", lambda: baselines.lloyd(rows, init=init)),
            _fitted("yinyang", "k=30", lambda: baselines.yinyang(rows, init=init)),
        ]
    )


@query("l_sampled")
def sampled(spark, d):
    return _fitted("sample and split", "k=20", lambda: baselines.sampled_kmeans(data.letter_rows(spark, d), 20))


@query("l_kmodes")
def kmodes(spark, d):
    return _fitted("k-modes", "k=20", lambda: baselines.kmodes(_coords(data.docs_sets(spark, d), 64), 20))


@query("l_kmeanspp")
def kmeanspp(spark, d):
    return baselines.kmeanspp_seeds(data.letter_rows(spark, d), 10).select("seed_id", F.size("vec").alias("dims"))


@query("l_kmeans_parallel")
def kmeans_parallel(spark, d):
    return baselines.kmeans_parallel_seeds(data.letter_rows(spark, d), 10).select("seed_id", F.size("vec").alias("dims"))


@query("l_mllib")
def mllib(spark, d):
    return baselines.mllib_kmeans(data.letter_rows(spark, d), 10).groupBy("cluster_id").agg(F.count("*").alias("size"))


@query("l_mllib_bisecting")
def mllib_bisecting(spark, d):
    return baselines.mllib_kmeans(data.letter_rows(spark, d), 8, bisecting=True).groupBy("cluster_id").agg(F.count("*").alias("size"))


@query("l_lsh_bisect")
def lsh_bisect(spark, d):
    return baselines.lsh_bisect(doph(data.docs_sets(spark, d), dims=64), "coords", 3).groupBy("cluster_id").agg(F.count("*").alias("size"))


@query("l_lsh_partition")
def lsh_partition(spark, d):
    return baselines.lsh_partition_cluster(data.letter_rows(spark, d), 5, 4).groupBy("cluster_id").agg(F.count("*").alias("size"))


# ---- workloads ----------------------------------------------------------------------------------


def _seeded(setting: str, run: threephase.Run) -> DataFrame:
    """One pass compares every row with every seed's center."""
    evaluations = run.rows.count() * run.centers.count()
    return _row("similar buckets", setting, run.assigned, sum(run.seconds.values())).withColumns(
        {"evaluations": F.lit(evaluations), "iterations": F.lit(1), "converged": F.lit(True)}
    )


def _k(run: threephase.Run) -> int:
    return max(2, asg.k_star(run.assigned).first()[0])


def _dense(rows: DataFrame, iterations: int = 100, **params) -> DataFrame:
    """The rivals go on until they converge or for ``iterations``; the row says which."""
    rows = staged(rows, "rows")
    run = threephase.cluster_dense(rows, **params)
    k = _k(run)
    text = ", ".join(f"{a}={b}" for a, b in params.items())
    return _union(
        [
            _seeded(text, run),
            _fitted("lloyd", f"k={k}", lambda: baselines.lloyd(rows, k, max_iter=iterations)),
            _fitted("yinyang", f"k={k}", lambda: baselines.yinyang(rows, k, max_iter=iterations)),
            _fitted("sample and split", f"k={k}", lambda: baselines.sampled_kmeans(rows, k, max_iter=iterations)),
        ]
    )


@query("w_dense_embeddings")
def w_embeddings(spark, d):
    return _dense(data.embedding_rows(spark, d), m=40, t=25, K=3, L=20, delta=2)


@query("w_dense_letters")
def w_letters(spark, d):
    return _dense(data.letter_rows(spark, d), m=40, t=10, K=3, L=10, delta=5)


@query("w_dense_lineitem")
def w_lineitem(spark, d):
    return _dense(data.lineitem_rows(spark, d), 20, m=20, t=50, K=3, L=10, delta=10)


def _modal(run: threephase.Run, setting: str) -> DataFrame:
    k = _k(run)
    return _union([_seeded(setting, run), _fitted("k-modes", f"k={k}", lambda: baselines.kmodes(run.rows, k, max_iter=20))])


@query("w_hetero_lineitem")
def w_hetero(spark, d):
    return _modal(threephase.cluster_hetero(data.nine_attributes(spark, d), *data.NINE, K_t=3, L_t=10, K=3, L=10, delta=10), "K_t=3, L_t=10")


@query("w_hetero_events")
def w_events(spark, d):
    return _modal(threephase.cluster_hetero(data.event_records(spark, d), *data.EVENT, K_t=2, L_t=10, K=3, L=10, delta=10), "K_t=2, L_t=10")


@query("w_hetero_orders")
def w_orders(spark, d):
    return _modal(threephase.cluster_hetero(data.order_records(spark, d), *data.ORDER, K_t=3, L_t=10, K=3, L=10, delta=10), "K_t=3, L_t=10")


@query("w_sparse_docs")
def w_docs(spark, d):
    return _modal(threephase.cluster_sparse(data.docs_sets(spark, d), K=3, L=10, delta=2), "D=400, K_t=2, L_t=20")


@query("w_sparse_baskets")
def w_baskets(spark, d):
    return _modal(threephase.cluster_sparse(data.basket_sets(spark, d), D=64, K_t=1, K=2, L=10, delta=2), "D=64, K_t=1, L_t=20")


@query("w_sparse_pages")
def w_pages(spark, d):
    return _modal(threephase.cluster_sparse(data.page_sets(spark, d), D=100, K=2, L=10, delta=2), "D=100, K_t=2, L_t=20")


@query("w_sparse_convs")
def w_convs(spark, d):
    return _modal(threephase.cluster_sparse(data.turn_sets(spark, d), D=64, K_t=1, K=2, L=10, delta=2), "D=64, K_t=1, L_t=20")


def _sweep(rows: DataFrame, base: dict, name: str, values: list) -> DataFrame:
    rows = staged(rows, "rows")
    out = []
    for v in values:
        run = threephase.cluster_dense(rows, **{**base, name: v})
        seeds = run.groups.agg(F.count_distinct("seed_id").alias("seeds"))
        out.append(_seeded(f"{name}={v}", run).crossJoin(seeds))
    return _union(out)


BASE = {"m": 20, "t": 20, "K": 3, "L": 10, "delta": 10}
query("w_impact_t")(lambda spark, d: _sweep(data.letter_rows(spark, d), BASE | {"delta": 5}, "t", [5, 10, 20, 40]))
query("w_impact_m")(lambda spark, d: _sweep(data.letter_rows(spark, d), BASE | {"delta": 5}, "m", [10, 20, 40]))
query("w_impact_l")(lambda spark, d: _sweep(data.letter_rows(spark, d), BASE | {"delta": 5}, "L", [5, 10, 20, 40]))
query("w_impact_k")(lambda spark, d: _sweep(data.letter_rows(spark, d), BASE | {"delta": 5}, "K", [2, 3, 4, 5]))
query("w_impact_delta")(lambda spark, d: _sweep(data.letter_rows(spark, d), BASE, "delta", [1, 10, 100]))


@query("w_grid")
def w_grid(spark, d):
    """A grid over t, m and L at fixed K and delta: the best run of each band of k*."""
    rows = staged(data.letter_rows(spark, d), "rows")

    def run(**params):
        got = threephase.cluster_dense(rows, K=3, delta=5, **params)
        s = metrics.radius_summary(got.assigned).first()
        return {"k_star": s["k_star"], "mean_radius": s["mean_radius"] or 0.0, "seconds": sum(got.seconds.values())}

    return best_by_band(grid_search(spark, run, combinations(t=[5, 20], m=[10, 20], L=[5, 10])), [10, 50, 200])


SEEDINGS = (("k-means++", baselines.kmeanspp_seeds), ("k-means||", baselines.kmeans_parallel_seeds), ("random", baselines.random_seeds))


def _seeding(rows: DataFrame, **params) -> DataFrame:
    """Seeding methods at the same k, one assignment each; seconds are the seeding's alone."""
    rows = staged(rows, "rows")
    run = threephase.cluster_dense(rows, **params)
    k = _k(run)
    out = [_row("similar buckets", f"k*={k}", run.assigned, run.seconds["transform"] + run.seconds["seed"])]
    for name, seeds in SEEDINGS:
        began = time.perf_counter()
        centers = staged(seeds(rows, k), "seeds")
        seconds = time.perf_counter() - began
        out.append(_row(name, f"k={k}", baselines.seed_eval(rows, centers), seconds))
    return _union(out)


def _delta(rows: DataFrame, share: int) -> int:
    """The least group size as a share of the rows, so that k stays alike over the table's sizes."""
    return max(5, rows.count() // share)


@query("w_seeding")
def w_seeding(spark, d):
    rows = data.letter_rows(spark, d)
    return _seeding(rows, m=40, t=10, K=3, L=10, delta=_delta(rows, 50))


@query("w_seeding_embeddings")
def w_seeding_embeddings(spark, d):
    return _seeding(data.embedding_rows(spark, d), m=40, t=10, K=3, L=10, delta=8)


@query("w_repeats")
def w_repeats(spark, d):
    """Means of five repeats with seeds of their own."""
    rows = staged(data.letter_rows(spark, d), "rows")
    delta, out = _delta(rows, 50), []

    def figures(assigned, seconds):
        s = metrics.radius_summary(assigned).first()
        return {"k_star": float(s["k_star"]), "mean_radius": s["mean_radius"], "max_radius": s["max_radius"], "seconds": seconds}

    def ours(seed):
        run = threephase.cluster_dense(rows, m=40, t=10, K=3, L=10, delta=delta, seed=seed)
        return figures(run.assigned, sum(run.seconds.values()))

    def random(k):
        def one(seed):
            began = time.perf_counter()
            found = staged(asg.assign(rows, staged(baselines.random_seeds(rows, k, seed), "seeds")), "assigned")
            return figures(found, time.perf_counter() - began)

        return one

    mean = metrics.repeat(ours)
    for name, got in (("similar buckets", mean), ("random", metrics.repeat(random(max(2, round(mean["k_star"])))))):
        out.append((name, 5, *[float(got[k]) for k in ("k_star", "mean_radius", "max_radius", "seconds")]))
    return spark.createDataFrame(out, "method string, repeats int, k_star double, mean_radius double, max_radius double, seconds double")


@query("w_local_parts")
def w_local_parts(spark, d):
    """One, two and four workers' shares voting locally: radius stays, seeds change little."""
    rows = staged(data.letter_rows(spark, d), "rows")
    out = []
    for g in (1, 2, 4):
        run = threephase.cluster_dense(rows, m=40, t=10, K=3, L=12, delta=5, vote="local", parts=g)
        out.append(_seeded(f"parts={g}", run))
    return _union(out)


@query("w_multi_load")
def w_multi_load(spark, d):
    rows = staged(data.letter_rows(spark, d), "rows")
    return _union([_seeded(f"batches={b}", threephase.cluster_dense(rows, m=40, t=10, K=3, L=10, delta=5, batches=b)) for b in (1, 2, 4)])


@query("w_load_balance")
def w_load_balance(spark, d):
    members = staged(tf.transform_dense(data.letter_rows(spark, d), "vec", 20, 10), "members")
    return _union(
        [metrics.imbalance(members, key, 8).select(F.lit(key).alias("dealt_by"), "most", "mean", "ratio") for key in ("table_id", "bucket_id")]
    )


@query("w_communication")
def w_communication(spark, d):
    """What the executed plans of a global and a local round exchange, and the groups that then move."""
    members = staged(tf.kl_buckets(data.docs_sets(spark, d), "tokens", 2, 6), "members")
    perms, out = draw(8, 0), []
    whole = seeding.seed_round(members, 2, 4, 2, perms)
    out.append(("global", metrics.exchanged(whole), whole.count()))
    with seeding.colocated(spark):
        local = seeding.local_round(members, 2, 4, 2, perms, 2)
        out.append(("local", metrics.exchanged(local), local.count()))
    return spark.createDataFrame(
        [(m, x["exchanges"], x["rows"], x["bytes"], n) for m, x, n in out],
        "vote string, exchanges int, rows bigint, bytes bigint, group_rows bigint",
    )


@query("w_seeding_slope")
def w_seeding_slope(spark, d):
    """Seconds of seeding against k, at the k that the seeded runs find for smaller and larger groups."""
    rows = staged(data.letter_rows(spark, d), "rows")
    members = staged(tf.transform_dense(rows, "vec", 40, 10), "members")
    points, n = [], rows.count()
    seeding.similar_bucket_seeds(members, 3, 10, n).count()  # the first run compiles
    for share in (10, 20, 50):
        began = time.perf_counter()
        groups = staged(seeding.similar_bucket_seeds(members, 3, 10, max(3, n // share)), "groups")
        k = max(2, groups.agg(F.count_distinct("group_id")).first()[0])
        points.append(("similar buckets", k, time.perf_counter() - began))
        for name, seeds in SEEDINGS:
            began = time.perf_counter()
            staged(seeds(rows, k), "seeds")
            points.append((name, k, time.perf_counter() - began))
    table = spark.createDataFrame(points, "method string, k_star bigint, seconds double")
    return _union([metrics.slope(table.filter(F.col("method") == m)).withColumn("method", F.lit(m)) for m in ("similar buckets", *[name for name, _ in SEEDINGS])])


@query("w_planted")
def w_planted(spark, d):
    """Planted balls, sets and mixed records: purity, and precision and recall over pairs."""
    out = []
    gauss = staged(planted_gauss(spark, 4000, 40, 16, 0.05), "planted")
    run = threephase.cluster_dense(gauss.select("id", "vec"), m=40, t=20, K=3, L=20, delta=10)
    out.append(("balls", run, gauss))
    sets = staged(planted_sets(spark, 1500, 50), "planted")
    out.append(("sets", threephase.cluster_sparse(sets.select("id", "tokens"), D=100, K=2, L=10, delta=3), sets))
    mixed = staged(planted_mixed(spark, 2000, 20), "planted")
    out.append(("mixed", threephase.cluster_hetero(mixed, ["x", "y"], ["a", "b", "c"], K_t=2, L_t=20, bins=20, K=2, L=10, delta=5), mixed))
    return _union(
        [
            metrics.purity(r.assigned, t).crossJoin(metrics.pair_pr(r.assigned, t)).crossJoin(asg.k_star(r.assigned)).select(
                F.lit(name).alias("data"), "purity", "precision", "recall", "k_star"
            )
            for name, r, t in out
        ]
    )


# ---- uses of the clusters -----------------------------------------------------------------------

_E = sql.embedding_rows() | sql.dense_members(EMB, EMB_T) | sql.seeding(3, 10, 2, draw(30, 0)) | sql.dedup(3, draw(3, 1)) | sql.NUMBERED | sql.centroids() | sql.assign_dense()
_MICRO = {"mg": "SELECT id, cluster_id AS seed_id FROM assigned"} | sql.centroids("mg", "micro")


def _assigned(spark, d):
    return staged(embedding_assigned(spark, d), "assigned")


@query(
    "x_micro_summary",
    sql.with_(_E | _MICRO, "SELECT a.cluster_id, any_value(array_to_string(m.vec, ',')) AS vec, any_value(m.size)::BIGINT AS size, round(max(dist), 3) AS radius FROM assigned a JOIN micro m ON m.seed_id = a.cluster_id GROUP BY a.cluster_id"),
)
def micro_summary(spark, d):
    out = micro.summarise(_assigned(spark, d), data.embedding_rows(spark, d), dims=64)
    return out.select("cluster_id", F.concat_ws(",", F.col("vec").cast("array<string>")).alias("vec"), "size", F.round("radius", 3).alias("radius"))


def _micro(spark, d):
    assigned = _assigned(spark, d)
    centers = staged(embedding_centers(spark, d), "centers").select(F.col("seed_id").alias("cluster_id"), "vec", "size")
    return centers.join(metrics.radii(assigned).select("cluster_id", "radius"), "cluster_id"), assigned


_D = lambda a, b: f"sqrt(list_sum(list_transform(range(1, 65), lambda i: (({a}[i] - {b}[i]) * ({a}[i] - {b}[i]))::DOUBLE)))"
_PROBE = {
    "q": "SELECT id AS qid, vec AS qvec FROM data WHERE id % 25 = 0",
    "near": f"SELECT qid, qvec, c.seed_id AS cluster_id FROM q, centers c WHERE c.seed_id IN (SELECT cluster_id FROM assigned) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {_D('qvec', 'c.vec')}, c.seed_id) <= 3",
    "found": f"SELECT qid, a.id, {_D('qvec', 'data.vec')} AS dist FROM near JOIN assigned a USING (cluster_id) JOIN data ON data.id = a.id",
}


@query(
    "x_ivf_search",
    sql.with_(_E | _PROBE, "SELECT qid, id, round(dist, 3) AS dist, (row_number() OVER (PARTITION BY qid ORDER BY dist, id))::INTEGER AS rank FROM found QUALIFY rank <= 5"),
)
def ivf_search(spark, d):
    clusters, assigned = _micro(spark, d)
    rows = data.embedding_rows(spark, d)
    q = rows.filter("id % 25 = 0").select(F.col("id").alias("qid"), "vec")
    return micro.search(clusters, assigned, rows, q, 3, 5).select("qid", "id", F.round("dist", 3).alias("dist"), "rank")


@query(
    "x_range_search",
    sql.with_(sql.embedding_rows(), f"SELECT q.id AS qid, b.id, round({_D('q.vec', 'b.vec')}, 3) AS dist FROM data q, data b WHERE q.id % 25 = 0 AND {_D('q.vec', 'b.vec')} <= 1200000"),
)
def range_search(spark, d):
    """Exact: the twin scans all rows, this passes over clusters whose ball can't reach."""
    rows, centers = data.embedding_rows(spark, d), staged(embedding_centers(spark, d), "centers")
    assigned = staged(asg.assign(rows, centers), "assigned")
    clusters = centers.withColumnRenamed("seed_id", "cluster_id").join(metrics.radii(assigned).select("cluster_id", "radius"), "cluster_id")
    q = rows.filter("id % 25 = 0").select(F.col("id").alias("qid"), "vec")
    return micro.range_search(clusters, assigned, rows, q, 1_200_000).select("qid", "id", F.round("dist", 3).alias("dist"))


@query("x_micro_hierarchy")
def micro_hierarchy(spark, d):
    return micro.hierarchy(_micro(spark, d)[0], 5)


@query("x_micro_density")
def micro_density(spark, d):
    return micro.density(_micro(spark, d)[0], 900_000, 2)
