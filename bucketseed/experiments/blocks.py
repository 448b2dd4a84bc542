"""Building blocks: token sets, hash values, buckets, projections, lookups."""

from __future__ import annotations

from pyspark.sql import functions as F

from bucketseed.experiments import data, sql
from bucketseed.functions import features as ft
from bucketseed.functions.doph import doph
from bucketseed.functions.minhash import minhash, minhash_values
from bucketseed.functions.permutations import draw
from bucketseed.functions.projection import dot, integer_directions
from bucketseed.operators import nns
from bucketseed.operators.postings import band_counts, similar_pairs
from bucketseed.operators.transform import kl_buckets, width_buckets
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


_SET = "id, len(tokens)::BIGINT AS n, coalesce(list_sum(tokens), 0)::BIGINT AS total"


def _summary(df):
    total = F.aggregate("tokens", F.lit(0).cast("bigint"), lambda s, x: s + x)
    return df.select("id", F.size("tokens").cast("bigint").alias("n"), total.alias("total"))


@query("b_token_ids", sql.with_(sql.docs_sets(), "SELECT t AS token, count(*)::BIGINT AS docs FROM (SELECT unnest(tokens) AS t FROM sets) GROUP BY t"))
def token_ids(spark, d):
    return data.docs_sets(spark, d).select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("docs"))


@query("b_word_sets", sql.with_(sql.docs_sets(), f"SELECT {_SET} FROM sets"))
def word_sets(spark, d):
    return _summary(data.docs_sets(spark, d))


_LOW = "lower(coalesce(text, ''))"


@query(
    "b_shingles",
    f"""WITH c AS (SELECT doc_id AS id, {_LOW} AS low, string_split({_LOW}, '') AS c FROM documents),
    g AS (SELECT id, CASE WHEN len(c) >= 5 THEN list_transform(range(1, len(c) - 3), lambda i: c[i] || c[i + 1] || c[i + 2] || c[i + 3] || c[i + 4]) ELSE [low] END AS g FROM c),
    sets AS (SELECT id, list_distinct(list_transform(g, lambda w: ('0x' || substr(md5(w), 1, 7))::BIGINT)) AS tokens FROM g) SELECT {_SET} FROM sets""",
)
def shingles(spark, d):
    docs = load(spark, d, "documents").select(F.col("doc_id").alias("id"), ft.shingle_set("text").alias("tokens"))
    return _summary(docs)


@query("b_baskets", sql.with_(sql.basket_sets(), f"SELECT {_SET} FROM sets"))
def baskets(spark, d):
    return _summary(data.basket_sets(spark, d))


SIX = draw(6, 11)


@query("b_minhash_docs", sql.with_(sql.docs_sets(), "SELECT id, " + ", ".join(f"{sql.minhash('tokens', SIX, i)} AS h{i}" for i in range(6)) + " FROM sets"))
def minhash_docs(spark, d):
    return data.docs_sets(spark, d).select("id", *[minhash("tokens", SIX, i).alias(f"h{i}") for i in range(6)])


TWELVE = draw(12, 0)
_MEMBERS = "SELECT bucket_id, table_id, id FROM members"


@query("b_kl_buckets_docs", sql.with_(sql.docs_sets() | sql.kl_members(2, 6, TWELVE), _MEMBERS))
def kl_docs(spark, d):
    return kl_buckets(data.docs_sets(spark, d), "tokens", 2, 6)


@query("b_kl_buckets_baskets", sql.with_(sql.basket_sets() | sql.kl_members(2, 6, TWELVE), _MEMBERS))
def kl_baskets(spark, d):
    return kl_buckets(data.basket_sets(spark, d), "tokens", 2, 6)


DIRS = integer_directions(10, 64, 3)


@query("b_project_embeddings", sql.with_(sql.embedding_rows() | sql.projected(DIRS), "SELECT table_id::INTEGER AS table_id, id, h FROM proj"))
def project_embeddings(spark, d):
    hs = F.array(*[dot("vec", x) for x in DIRS])
    return data.embedding_rows(spark, d).select("id", F.posexplode(hs).alias("table_id", "h"))


OFFSETS = [1e6 * i for i in range(10)]


@query(
    "b_width_buckets",
    sql.with_(
        sql.embedding_rows() | sql.projected(DIRS),
        "SELECT table_id::VARCHAR || ':' || floor((h::DOUBLE + table_id * 1000000.0) / 200000000.0)::BIGINT::VARCHAR AS bucket_id, table_id::INTEGER AS table_id, id FROM proj",
    ),
)
def width_embeddings(spark, d):
    return width_buckets(data.embedding_rows(spark, d), "vec", DIRS, OFFSETS, 2e8)


@query("b_doph_docs", sql.with_(sql.docs_sets() | sql.doph_coords(64, 5), "SELECT id, array_to_string(coords, ',') AS coords FROM coords"))
def doph_docs(spark, d):
    coords = doph(data.docs_sets(spark, d), dims=64, seed=5)
    return coords.select("id", F.concat_ws(",", F.col("coords").cast("array<string>")).alias("coords"))


W = 100_000_000


def _probes(rows):
    """Every tenth vector is a query against all rows: the stated query set."""
    return rows.filter("id % 10 = 0").select(F.col("id").alias("qid"), "vec")


_COLLIDE = {
    "hits": f"SELECT q.id AS qid, b.id, count(*) AS collisions FROM proj q JOIN proj b ON b.table_id = q.table_id AND 2 * abs(b.h - q.h) <= {W} WHERE q.id % 10 = 0 GROUP BY q.id, b.id"
}


@query("b_collision_counts", sql.with_(sql.embedding_rows() | sql.projected(DIRS) | _COLLIDE, "SELECT qid, id, collisions::BIGINT AS collisions FROM hits"))
def collision_counts(spark, d):
    rows = data.embedding_rows(spark, d)
    return nns.collision_counts(rows, _probes(rows), DIRS, W)


_EXACT = "sqrt(list_sum(list_transform(range(1, len(b.vec) + 1), lambda i: ((b.vec[i] - q.vec[i]) * (b.vec[i] - q.vec[i]))::DOUBLE)))"


@query(
    "b_qalsh_nns",
    sql.with_(
        sql.embedding_rows() | sql.projected(DIRS) | _COLLIDE,
        f"SELECT qid, id, round(dist, 3) AS dist, rank FROM (SELECT h.qid, h.id, {_EXACT} AS dist, (row_number() OVER (PARTITION BY h.qid ORDER BY {_EXACT}, h.id))::INTEGER AS rank FROM hits h JOIN data b ON b.id = h.id JOIN data q ON q.id = h.qid WHERE collisions > 4) WHERE rank <= 10",
    ),
)
def qalsh(spark, d):
    rows = data.embedding_rows(spark, d)
    found = nns.qalsh_nns(rows, _probes(rows), DIRS, W, 4, 10)
    return found.select("qid", "id", F.round("dist", 3).alias("dist"), "rank")


_PAIRS = {
    "sizes": "SELECT id, len(tokens) AS n FROM sets",
    "cells": "SELECT id, unnest(tokens) AS t FROM sets",
    "both_": "SELECT a.id AS a, b.id AS b, count(*) AS c FROM cells a JOIN cells b ON a.t = b.t AND a.id < b.id GROUP BY a.id, b.id",
    "pairs": "SELECT p.a, p.b, p.c / (x.n + y.n - p.c) AS jaccard FROM both_ p JOIN sizes x ON x.id = p.a JOIN sizes y ON y.id = p.b",
}


@query("b_exact_pairs", sql.with_(sql.docs_sets() | _PAIRS, "SELECT a, b, round(jaccard, 9) AS jaccard FROM pairs WHERE jaccard >= 0.5"))
def exact_pairs(spark, d):
    return nns.exact_pairs(data.docs_sets(spark, d), 0.5).select("a", "b", F.round("jaccard", 9).alias("jaccard"))


_SAME = " + ".join(f"(x.h{i} = y.h{i})::INTEGER" for i in range(6))


@query(
    "b_collision_curve",
    sql.with_(
        sql.docs_sets() | _PAIRS | {"hashed": "SELECT id, " + ", ".join(f"{sql.minhash('tokens', SIX, i)} AS h{i}" for i in range(6)) + " FROM sets"},
        f"SELECT least(floor((1 - jaccard) * 10), 9)::INTEGER AS band, count(*)::BIGINT AS pairs, sum({_SAME})::BIGINT AS same FROM pairs JOIN hashed x ON x.id = a JOIN hashed y ON y.id = b GROUP BY 1",
    ),
)
def collision_curve(spark, d):
    """Equal hashes (of six) by distance band: the rate falls with distance."""
    sets = data.docs_sets(spark, d)
    return band_counts(sets.select("id", "tokens", minhash_values("tokens", SIX).alias("h")), len(SIX))


NNS = draw(20, 21)
_BENCH = {"q": f"SELECT item_id AS qid, {sql.WORDS.format(text='text')} AS qtokens FROM benchmark"}


def _sig(K, L, tokens, perms):
    return "[" + ", ".join(
        "{'l': %d, 's': %s}" % (l, " || '_' || ".join(f"({sql.minhash(tokens, perms, l * K + k)})::VARCHAR" for k in range(K))) for l in range(L)
    ) + "]"


@query(
    "b_minhash_nns",
    sql.with_(
        sql.docs_sets() | _BENCH | {
            "bs": f"SELECT id, unnest({_sig(1, 20, 'tokens', NNS)}) AS s FROM sets",
            "qs": f"SELECT qid, unnest({_sig(1, 20, 'qtokens', NNS)}) AS s FROM q",
            "cand": "SELECT DISTINCT qid, id FROM qs JOIN bs ON qs.s = bs.s",
            "d": "SELECT c.qid, c.id, 1 - len(list_intersect(q.qtokens, s.tokens)) / (len(q.qtokens) + len(s.tokens) - len(list_intersect(q.qtokens, s.tokens))) AS dist FROM cand c JOIN q ON q.qid = c.qid JOIN sets s ON s.id = c.id",
            "r": "SELECT qid, id, dist, (row_number() OVER (PARTITION BY qid ORDER BY dist, id))::INTEGER AS rank FROM d",
        },
        "SELECT qid, id, round(dist, 9) AS dist, rank FROM r WHERE rank <= 5",
    ),
)
def minhash_lookup(spark, d):
    q = load(spark, d, "benchmark").select(F.col("item_id").alias("qid"), ft.word_set("text").alias("tokens"))
    return nns.minhash_nns(data.docs_sets(spark, d), q, 1, 20, 5, perms=NNS).select("qid", "id", F.round("dist", 9).alias("dist"), "rank")


@query(
    "b_simhash",
    sql.with_(
        sql.embedding_rows() | sql.projected(DIRS),
        "SELECT id, string_agg(CASE WHEN h >= 0 THEN '1' ELSE '0' END, '' ORDER BY table_id) AS bits FROM proj GROUP BY id",
    ),
)
def simhash(spark, d):
    return data.embedding_rows(spark, d).select(
        "id", F.concat(*[F.when(dot("vec", x) >= 0, "1").otherwise("0") for x in DIRS]).alias("bits")
    )


@query("b_doph_estimate")
def doph_estimate(spark, d):
    """Pairs of similar documents: exact similarity beside what 400 densified coordinates estimate."""
    return similar_pairs(doph(data.docs_sets(spark, d), dims=400, seed=3, keep=("tokens",)), 0.5)


@query("b_similarity_join")
def similarity_join(spark, d):
    q = load(spark, d, "benchmark").select(F.col("item_id").alias("qid"), ft.word_set("text").alias("tokens"))
    return nns.similarity_join(q, data.docs_sets(spark, d), 0.2)


@query("b_sensitivity")
def sensitivity(spark, d):
    """Collision rate of one function by band, with the built-in band function."""
    curve = collision_curve(spark, d)
    return curve.select("band", "pairs", (F.col("same") / (6 * F.col("pairs"))).alias("rate"))


