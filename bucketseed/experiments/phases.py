"""The three phases on the given tables: buckets, seeds, centers and one assignment."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.experiments import data, sql
from bucketseed.functions.doph import doph
from bucketseed.functions.permutations import draw
from bucketseed.functions.projection import integer_directions
from bucketseed.operators import assign as asg
from bucketseed.operators import metrics, seeding
from bucketseed.operators import transform as tf
from bucketseed.operators.centers import centroids, modes, numbered
from bucketseed.staging import staged
from bucketseed.tables import load

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


_MEMBERS = "SELECT bucket_id, table_id, id FROM members"

# ---- transformation -------------------------------------------------------------------------

EMB = integer_directions(20, 64, 1)
LIN = integer_directions(20, 4, 2)
LET = integer_directions(20, 26, 4)
EMB_T, LIN_T, LET_T = 25, 30, 10


def embedding_members(spark, d, mode="ranked"):
    return tf.transform_dense(data.embedding_rows(spark, d), "vec", 20, EMB_T, mode=mode, directions=EMB)


def lineitem_members(spark, d, mode="ranked"):
    return tf.transform_dense(data.lineitem_rows(spark, d), "vec", 20, LIN_T, mode=mode, directions=LIN)


_EMB = sql.embedding_rows() | sql.dense_members(EMB, EMB_T)
_LIN = sql.lineitem_rows() | sql.dense_members(LIN, LIN_T)
_LET = sql.letter_rows() | sql.dense_members(LET, LET_T)

query("t_dense_embeddings", sql.with_(_EMB, _MEMBERS))(embedding_members)
query("t_dense_lineitem", sql.with_(_LIN, _MEMBERS))(lineitem_members)
query("t_ranked_equals_window", sql.with_(_LIN, _MEMBERS))(lambda spark, d: lineitem_members(spark, d, "ranked"))
query("t_window_cut", sql.with_(_EMB, _MEMBERS))(lambda spark, d: embedding_members(spark, d, "window"))


@query("t_dense_letters", sql.with_(_LET, _MEMBERS))
def letter_members(spark, d):
    return tf.transform_dense(data.letter_rows(spark, d), "vec", 20, LET_T, directions=LET)


@query("t_quantile_cut")
def quantile_cut(spark, d):
    return tf.bucket_stats(lineitem_members(spark, d, "quantile"))


_CENTERED = sql.embedding_rows() | sql.projected(EMB[:2]) | {
    "near": "SELECT a.table_id::VARCHAR || ':' || a.id::VARCHAR AS bucket_id, count(*)::BIGINT AS n FROM proj a JOIN proj b ON a.table_id = b.table_id AND abs(a.h - b.h) <= 2.5e7 GROUP BY ALL"
}


@query("t_centered_buckets", sql.with_(_CENTERED, "SELECT * FROM near"))
def centered(spark, d):
    """Overlapping buckets of width 0.05 over two projections, as counts by bucket."""
    rows = data.embedding_rows(spark, d)
    return tf.centered_buckets(rows, "vec", EMB[:2], 5e7).groupBy("bucket_id").agg(F.count("*").alias("n"))


_NINE = {
    "rows": f"SELECT row_number() OVER (ORDER BY {sql.LINEITEM_ORDER}) AS id, * FROM lineitem",
    "nine": "SELECT id, " + ", ".join([*data.NINE[0], *data.NINE[1]]) + " FROM rows JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey",
}


def _cut(cols, bins, tie="split"):
    part = (
        (lambda c: f"ntile({bins}) OVER (ORDER BY {c}, id) - 1")
        if tie == "split"
        else (lambda c: f"least(floor(percent_rank() OVER (ORDER BY {c}) * {bins}), {bins - 1})::INTEGER")
    )
    return ", ".join(f"{part(c)} AS {c}" for c in cols)


@query("t_discretise", sql.with_(_NINE, f"SELECT id, {_cut(data.NINE[0], 10)} FROM nine"))
def discretised(spark, d):
    return tf.discretise(data.nine_attributes(spark, d).select("id", *data.NINE[0]), data.NINE[0], 10)


@query("t_discretise_ties", sql.with_(_NINE, f"SELECT id, {_cut(['l_discount', 'l_tax'], 10, 'together')} FROM nine"))
def discretised_together(spark, d):
    return tf.discretise(data.nine_attributes(spark, d).select("id", "l_discount", "l_tax"), ["l_discount", "l_tax"], 10, "together")


def _record(numeric, categorical, source, bins=10):
    tokens = ", ".join(sql.token(f"'{c}=' || coalesce({c}::VARCHAR, '\\0')") for c in [*numeric, *categorical])
    plain = ", ".join(categorical)
    return {
        "cut": f"SELECT id, {_cut(numeric, bins) + ', ' if numeric else ''}{plain} FROM {source}",
        "sets": f"SELECT id, [{tokens}] AS tokens FROM cut",
    }


K3 = draw(30, 0)
_HET = _NINE | _record(*data.NINE, "nine") | sql.kl_members(3, 10, K3)


@query("t_hetero_lineitem", sql.with_(_HET, _MEMBERS))
def hetero_members(spark, d):
    return tf.transform_hetero(data.nine_attributes(spark, d), *data.NINE, 3, 10)


_EVENTS = {
    "ev": "SELECT event_id AS id, value, hour(ts) AS hour, json_extract_string(props, '$.k')::BIGINT AS k, event_type FROM events"
}


@query("t_hetero_events", sql.with_(_EVENTS | _record(*data.EVENT, "ev") | sql.kl_members(2, 6, draw(12, 0)), _MEMBERS))
def event_members(spark, d):
    return tf.transform_hetero(data.event_records(spark, d), *data.EVENT, 2, 6)


_ORDERS = {"oc": "SELECT o_orderkey AS id, " + ", ".join([*data.ORDER[0], *data.ORDER[1]]) + " FROM orders JOIN customer ON c_custkey = o_custkey"}


@query("t_hetero_orders", sql.with_(_ORDERS | _record(*data.ORDER, "oc") | sql.kl_members(2, 6, draw(12, 0)), _MEMBERS))
def order_members(spark, d):
    return tf.transform_hetero(data.order_records(spark, d), *data.ORDER, 2, 6)


_PART = ["p_brand", "p_type", "p_name"]


@query(
    "t_categorical_part",
    sql.with_({"pt": "SELECT p_partkey AS id, p_brand, p_type, p_name FROM part"} | _record([], _PART, "pt") | sql.kl_members(2, 6, draw(12, 0)), _MEMBERS),
)
def part_members(spark, d):
    spec = tf.DatasetSpec("categorical", "p_partkey", categorical=tuple(_PART), params={"K": 2, "L": 6})
    return tf.to_buckets(load(spark, d, "part"), spec)


JOINT = integer_directions(6, 4, 9)
_JOINT = sql.lineitem_rows() | sql.projected(JOINT) | {
    "parts": "SELECT id, table_id, ntile(20) OVER (PARTITION BY table_id ORDER BY h, id) - 1 AS part FROM proj",
    "sets": f"SELECT id, list({sql.token(chr(39) + 'p' + chr(39) + ' || table_id::VARCHAR || ' + chr(39) + '=' + chr(39) + ' || part::VARCHAR')} ORDER BY table_id) AS tokens FROM parts GROUP BY id",
}


@query("t_discretise_joint", sql.with_(_JOINT, "SELECT id, array_to_string(tokens, ',') AS tokens FROM sets"))
def joint(spark, d):
    rows = data.lineitem_rows(spark, d).select("id", *[F.col("vec")[i].alias(f"v{i}") for i in range(4)])
    out = tf.joint_tokens(rows, [f"v{i}" for i in range(4)], [], 6, 20, directions=JOINT)
    return out.select("id", F.concat_ws(",", F.col("tokens").cast("array<string>")).alias("tokens"))


_SPARSE = sql.docs_sets() | sql.doph_coords(64, 0) | sql.COORD_SETS | sql.kl_members(2, 10, draw(20, 1), "csets")


@query("t_sparse_docs", sql.with_(_SPARSE, _MEMBERS))
def sparse_members(spark, d):
    return tf.transform_sparse(data.docs_sets(spark, d), "tokens", 2, 10, 64)


@query("t_sparse_docs_400")
def sparse_members_400(spark, d):
    return tf.bucket_stats(tf.transform_sparse(data.docs_sets(spark, d), "tokens", 2, 20, 400))


@query("t_sparse_pages", sql.with_(sql.page_sets() | sql.kl_members(2, 6, draw(12, 0)), _MEMBERS))
def page_members(spark, d):
    return tf.transform_sparse(data.page_sets(spark, d), "tokens", 2, 6, None)


_STATS = "SELECT count(*)::BIGINT AS n_buckets, sum(n)::BIGINT AS n_members, sum(n) / count(*) AS mean_size, max(n)::BIGINT AS max_size, sum((n = 1)::INTEGER)::BIGINT AS singletons FROM (SELECT count(*) AS n FROM members GROUP BY bucket_id)"


@query("t_bucket_stats", sql.with_(sql.docs_sets() | sql.kl_members(2, 6, draw(12, 0)), _STATS))
def stats(spark, d):
    return tf.bucket_stats(docs_members(spark, d))


# ---- seeding --------------------------------------------------------------------------------

DK, DL, DDELTA = 2, 4, 2
P1, P2 = draw(DK * DL, 0), draw(DK, 1)
_DOCS = sql.docs_sets() | sql.kl_members(2, 6, draw(12, 0))


def docs_members(spark, d) -> DataFrame:
    return tf.kl_buckets(data.docs_sets(spark, d), "tokens", 2, 6)


_GROUPS = "SELECT group_id, id, votes::BIGINT AS votes, bin_size::BIGINT AS bin_size FROM "


@query(
    "s_bucket_signatures",
    sql.with_(_DOCS | sql.seeding(DK, DL, 1, P1), "SELECT bucket_id, size::BIGINT AS size, " + ", ".join(f"h{i}" for i in range(DK * DL)) + " FROM sigs"),
)
def signatures(spark, d):
    return seeding.bucket_signatures(docs_members(spark, d), P1)


@query("s_bins", sql.with_(_DOCS | sql.seeding(DK, DL, 1, P1, prune=False), "SELECT bin_id, bin_table, bucket_id, bin_size::BIGINT AS bin_size FROM bins"))
def bins(spark, d):
    return seeding.make_bins(signatures(spark, d), DK, DL, prune=False)


@query("s_vote", sql.with_(_DOCS | sql.seeding(DK, DL, 1, P1, prune=False), _GROUPS + "voted"))
def vote(spark, d):
    members = staged(docs_members(spark, d), "members")
    return seeding.majority_vote(seeding.make_bins(seeding.bucket_signatures(members, P1), DK, DL, prune=False), members)


@query("s_vote_delta", sql.with_(_DOCS | sql.seeding(DK, DL, DDELTA, P1, prune=False), _GROUPS + "groups"))
def vote_delta(spark, d):
    return seeding.at_least(vote(spark, d), DDELTA)


@query("s_prune", sql.with_(_DOCS | sql.seeding(DK, DL, DDELTA, P1, prune=False), _GROUPS + "groups"))
def pruned(spark, d):
    """The bound drops bins before the vote; the twin doesn't use it and gets the same groups."""
    return seeding.seed_round(staged(docs_members(spark, d), "members"), DK, DL, DDELTA, P1, prune=True)


_FULL = _DOCS | sql.seeding(DK, DL, DDELTA, P1) | sql.dedup(DK, P2)


def docs_seeds(spark, d, **options):
    return seeding.similar_bucket_seeds(staged(docs_members(spark, d), "members"), DK, DL, DDELTA, **options)


query("s_full_docs", sql.with_(_FULL, _GROUPS + "seeds"))(docs_seeds)
query("s_dedup_keep", sql.with_(_FULL, "SELECT count(DISTINCT group_id)::BIGINT AS seeds, count(*)::BIGINT AS ids FROM seeds"))(
    lambda spark, d: docs_seeds(spark, d).agg(F.count_distinct("group_id").alias("seeds"), F.count("*").alias("ids"))
)
query("s_dedup_drop", sql.with_(_DOCS | sql.seeding(DK, DL, DDELTA, P1) | sql.dedup(DK, P2, singletons="drop"), _GROUPS + "seeds"))(
    lambda spark, d: docs_seeds(spark, d, singletons="drop")
)
_FIRST = {
    "ranked": "SELECT min(group_id) AS group_id FROM (SELECT group_id, list_sort(list(id)) AS ids FROM groups GROUP BY group_id) GROUP BY ids",
    "firsts": "SELECT * FROM groups WHERE group_id IN (SELECT group_id FROM ranked)",
}
_EXACT_FIRST = _DOCS | sql.seeding(DK, DL, DDELTA, P1) | _FIRST | sql.dedup(DK, P2, "firsts")
query("s_exact_first", sql.with_(_EXACT_FIRST, "SELECT DISTINCT list_sort(list(id)) ::VARCHAR AS ids FROM seeds GROUP BY group_id"))(
    lambda spark, d: seeding.dedup_groups(
        staged(seeding.seed_round(staged(docs_members(spark, d), "members"), DK, DL, DDELTA, P1), "groups"), DK, perms=P2, exact_first=True
    ).groupBy("group_id").agg(F.concat(F.lit("["), F.array_join(F.sort_array(F.collect_list("id")).cast("array<string>"), ", "), F.lit("]")).alias("ids")).select("ids").distinct()
)

_LOCAL = _DOCS | sql.seeding(DK, DL, DDELTA, P1, parts=2) | sql.dedup(DK, P2)
query("s_local_vote", sql.with_(_LOCAL, _GROUPS + "seeds"))(lambda spark, d: docs_seeds(spark, d, vote="local", parts=2))


@query("s_multi_load", sql.with_(_LOCAL, "SELECT id, votes::BIGINT AS votes, bin_size::BIGINT AS bin_size FROM seeds"))
def multi_load(spark, d):
    """Two batches of tables, each seeded alone: the same groups as two workers voting locally."""
    return docs_seeds(spark, d, batches=2).select("id", "votes", "bin_size")


def _share(theta):
    return {
        "na": "SELECT group_id, count(*) AS na FROM g_seeds GROUP BY 1",
        "nb": "SELECT group_id AS other, count(*) AS nb FROM l_seeds GROUP BY 1",
        "both_": "SELECT a.group_id, b.group_id AS other, count(*) AS c FROM g_seeds a JOIN l_seeds b ON a.id = b.id GROUP BY 1, 2",
        "twins": f"SELECT DISTINCT group_id FROM both_ JOIN na USING (group_id) JOIN nb USING (other) WHERE c >= {theta} * (na + nb - c)",
    }


_G = sql.seeding(DK, DL, DDELTA, P1, out="g_groups", p="g_") | {"g_buckets": "SELECT group_id AS bucket_id, id FROM g_groups"} | sql.seeding(DK, 1, 1, P2, "g_buckets", "g_seeds", 1, prune=False, p="gd_")
_L = sql.seeding(DK, DL, DDELTA, P1, out="l_groups", p="l_", parts=2) | {"l_buckets": "SELECT group_id AS bucket_id, id FROM l_groups"} | sql.seeding(DK, 1, 1, P2, "l_buckets", "l_seeds", 1, prune=False, p="ld_")


@query("s_local_vs_global", sql.with_(_DOCS | _G | _L | _share(0.5), "SELECT (SELECT count(*) FROM na)::BIGINT AS groups, (SELECT count(*) FROM twins)::BIGINT AS with_twin"))
def local_vs_global(spark, d):
    members = staged(docs_members(spark, d), "members")
    whole = staged(seeding.similar_bucket_seeds(members, DK, DL, DDELTA), "whole")
    local = staged(seeding.similar_bucket_seeds(members, DK, DL, DDELTA, vote="local", parts=2), "local")
    return metrics.group_overlap(whole, local, 0.5)


LK, LL, LDELTA = 3, 10, 10
L1, L2 = draw(LK * LL, 0), draw(LK, 1)
_LSEEDS = _LIN | sql.seeding(LK, LL, LDELTA, L1) | sql.dedup(LK, L2)


def lineitem_seeds(spark, d):
    return seeding.similar_bucket_seeds(staged(lineitem_members(spark, d), "members"), LK, LL, LDELTA)


query("s_full_lineitem", sql.with_(_LSEEDS, _GROUPS + "seeds"))(lineitem_seeds)
query("s_full_hetero", sql.with_(_HET | sql.seeding(LK, LL, LDELTA, L1) | sql.dedup(LK, L2), _GROUPS + "seeds"))(
    lambda spark, d: seeding.similar_bucket_seeds(staged(hetero_members(spark, d), "members"), LK, LL, LDELTA)
)


@query(
    "s_seed_stats",
    sql.with_(
        _DOCS | sql.seeding(DK, DL, DDELTA, P1) | sql.dedup(DK, P2),
        "SELECT (SELECT count(DISTINCT group_id) FROM voted)::BIGINT AS raw_groups, (SELECT count(DISTINCT group_id) FROM groups)::BIGINT AS large_groups, (SELECT count(DISTINCT group_id) FROM seeds)::BIGINT AS seeds, (SELECT count(*) FROM seeds)::BIGINT AS seed_ids",
    ),
)
def seed_stats(spark, d):
    members = staged(docs_members(spark, d), "members")
    sigs = seeding.bucket_signatures(members, P1)
    raw = staged(seeding.majority_vote(seeding.make_bins(sigs, DK, DL, 2, DDELTA), members), "raw")
    kept = staged(seeding.at_least(raw, DDELTA), "kept")
    return seeding.seed_stats(raw, kept, seeding.dedup_groups(kept, DK, perms=P2))


# ---- centers and assignment -------------------------------------------------------------------

EK, EL, EDELTA = 3, 10, 2
E1, E2 = draw(EK * EL, 0), draw(EK, 1)
_ESEEDS = _EMB | sql.seeding(EK, EL, EDELTA, E1) | sql.dedup(EK, E2) | sql.NUMBERED
_ECENT = _ESEEDS | sql.centroids()
_EASSIGN = _ECENT | sql.assign_dense()


def embedding_centers(spark, d):
    groups = numbered(staged(seeding.similar_bucket_seeds(staged(embedding_members(spark, d), "members"), EK, EL, EDELTA), "seeds"))
    return centroids(groups, data.embedding_rows(spark, d), dims=64)


def embedding_assigned(spark, d, strategy="sql"):
    return asg.assign(data.embedding_rows(spark, d), staged(embedding_centers(spark, d), "centers"), strategy=strategy)


@query("a_centroids", sql.with_(_ECENT, "SELECT seed_id, array_to_string(vec, ',') AS vec, size::BIGINT AS size FROM centers"))
def centroid_rows(spark, d):
    return embedding_centers(spark, d).select("seed_id", F.concat_ws(",", F.col("vec").cast("array<string>")).alias("vec"), "size")


_SSEEDS = _SPARSE | sql.seeding(DK, DL, DDELTA, P1) | sql.dedup(DK, P2) | sql.NUMBERED
_SMODES = _SSEEDS | sql.modes()


def sparse_seeded(spark, d):
    """Token rows and mode centers of the sparse pipeline (D = 64, exact)."""
    coords = doph(data.docs_sets(spark, d), dims=64)
    rows = staged(coords.select("id", tf.coordinate_tokens("coords").alias("tokens")), "coords")
    members = staged(tf.kl_buckets(rows, "tokens", 2, 10, 1), "members")
    groups = numbered(staged(seeding.similar_bucket_seeds(members, DK, DL, DDELTA), "seeds"))
    return rows, staged(modes(groups, rows), "centers")


@query("a_modes", sql.with_(_SMODES, "SELECT seed_id, array_to_string(modes, ',') AS modes, size::BIGINT AS size FROM centers"))
def mode_rows(spark, d):
    return sparse_seeded(spark, d)[1].select("seed_id", F.concat_ws(",", F.col("modes").cast("array<string>")).alias("modes"), "size")


_HSEEDS = _HET | sql.seeding(LK, LL, LDELTA, L1) | sql.dedup(LK, L2) | sql.NUMBERED
_HMODES = _HSEEDS | sql.modes(source="sets")


def hetero_seeded(spark, d):
    """Token rows and mode centers of the nine-attribute records."""
    rows = staged(tf.hetero_tokens(data.nine_attributes(spark, d), *data.NINE), "tokens")
    members = staged(tf.kl_buckets(rows, "tokens", 3, 10), "members")
    groups = numbered(staged(seeding.similar_bucket_seeds(members, LK, LL, LDELTA), "seeds"))
    return rows, staged(modes(groups, rows), "centers")


@query("a_modes_hetero", sql.with_(_HMODES, "SELECT seed_id, array_to_string(modes, ',') AS modes, size::BIGINT AS size FROM centers"))
def hetero_mode_rows(spark, d):
    return hetero_seeded(spark, d)[1].select("seed_id", F.concat_ws(",", F.col("modes").cast("array<string>")).alias("modes"), "size")


_OUT = "SELECT id, cluster_id, round(dist, 6) AS dist FROM assigned"
_ROUND = lambda df: df.select("id", "cluster_id", F.round("dist", 6).alias("dist"))

query("a_assign_dense", sql.with_(_EASSIGN, _OUT))(lambda spark, d: _ROUND(embedding_assigned(spark, d)))


@query("a_assign_match", sql.with_(_SMODES | sql.assign_match(), _OUT))
def assign_match(spark, d):
    rows, centers = sparse_seeded(spark, d)
    return _ROUND(asg.assign(rows, centers, strategy="match", vec="tokens", center="modes"))


_TWO = _ECENT | sql.assign_dense("first_") | {"again": "SELECT id, cluster_id AS seed_id FROM first_"} | sql.centroids("again", "moved") | sql.assign_dense("assigned", "moved")


@query("a_two_passes", sql.with_(_TWO, _OUT))
def two_passes(spark, d):
    return _ROUND(asg.assign_passes(data.embedding_rows(spark, d), staged(embedding_centers(spark, d), "centers"), 2, strategy="sql"))


@query("a_radius", sql.with_(_EASSIGN, sql.RADIUS))
def radius(spark, d):
    return _summary(embedding_assigned(spark, d))


def _summary(assigned):
    s = metrics.radius_summary(assigned)
    return s.select("k_star", "n", *[F.round(c, 6).alias(c) for c in ("mean_radius", "max_radius", "weighted_radius")])


@query("a_kstar", sql.with_(_EASSIGN, "SELECT count(DISTINCT cluster_id)::BIGINT AS k_star FROM assigned"))
def kstar(spark, d):
    return asg.k_star(embedding_assigned(spark, d))


@query("a_objective", sql.with_(_EASSIGN, "SELECT sum(round(dist)::BIGINT)::BIGINT AS total_distance FROM assigned"))
def objective(spark, d):
    return embedding_assigned(spark, d).agg(F.sum(F.round("dist").cast("bigint")).alias("total_distance"))


@query("a_gemm_equals_sql", sql.with_(_EASSIGN, "SELECT id, cluster_id FROM assigned"))
def gemm(spark, d):
    return embedding_assigned(spark, d, "gemm").select("id", "cluster_id")


@query("a_assign_hetero", sql.with_(_HMODES | sql.assign_match(source="sets"), _OUT))
def assign_hetero(spark, d):
    rows, centers = hetero_seeded(spark, d)
    return _ROUND(asg.assign(rows, centers, "jaccard_tokens", vec="tokens", center="modes"))


@query("a_shortlist")
def shortlist(spark, d):
    """Rows, and how many get the full scan's center, or one as near, from the shortlist."""
    rows, centers = sparse_seeded(spark, d)
    short = asg.assign(rows, centers, strategy="shortlist", vec="tokens", center="modes")
    full = asg.assign(rows, centers, "jaccard_tokens", vec="tokens", center="modes")
    both = short.join(full.select("id", F.col("cluster_id").alias("best"), F.col("dist").alias("least")), "id")
    return both.agg(
        F.count("*").alias("rows"),
        F.sum((F.col("cluster_id") == F.col("best")).cast("bigint")).alias("same_center"),
        F.sum((F.col("dist") <= F.col("least") + 1e-9).cast("bigint")).alias("as_near"),
    )


@query("a_radius_ranks", sql.with_(_EASSIGN, "SELECT cluster_id, size, (rank() OVER (ORDER BY radius DESC))::INTEGER AS rnk, (dense_rank() OVER (ORDER BY size))::INTEGER AS by_size, round(cume_dist() OVER (ORDER BY size), 9) AS share FROM (SELECT cluster_id, count(*)::BIGINT AS size, round(max(dist), 3) AS radius FROM assigned GROUP BY cluster_id)"))
def radius_ranks(spark, d):
    per = metrics.radii(embedding_assigned(spark, d)).withColumn("radius", F.round("radius", 3))
    return per.select(
        "cluster_id", "size", F.rank().over(Window.orderBy(F.desc("radius"))).alias("rnk"),
        F.dense_rank().over(Window.orderBy("size")).alias("by_size"),
        F.round(F.cume_dist().over(Window.orderBy("size")), 9).alias("share"),
    )
