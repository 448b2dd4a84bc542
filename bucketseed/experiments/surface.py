"""Relational, function and streaming surface on the given tables."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from bucketseed.experiments import data, sql
from bucketseed.functions import sql_surface
from bucketseed.functions.permutations import draw
from bucketseed.operators.metrics import radii
from bucketseed.staging import stage_folder
from bucketseed.streaming import scoring
from bucketseed.tables import load, register

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


def both(name: str, text: str, twin: str | None = None):
    """The same statement in both engines, over registered views."""

    def run(spark, d):
        register(spark, d)
        return spark.sql(text)

    query(name, twin or text)(run)


both(
    "o_rollup_report",
    "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity, CAST(grouping(l_returnflag) + grouping(l_linestatus) AS BIGINT) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
)
both(
    "o_cube_report",
    "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
)
both(
    "o_grouping_sets",
    "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())",
)


@query(
    "o_pivot",
    "SELECT l_returnflag, sum((l_linestatus = 'F')::INTEGER)::BIGINT AS F, sum((l_linestatus = 'O')::INTEGER)::BIGINT AS O FROM lineitem GROUP BY l_returnflag",
)
def pivot(spark, d):
    rows = load(spark, d, "lineitem")
    return rows.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0)


both("o_topk_price", "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20")
both("o_semi", "SELECT doc_id, lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
both("o_anti", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
both(
    "o_full_outer",
    "SELECT coalesce(n.n_name, 'none') AS n_name, coalesce(s.s, 0) AS s FROM nation n FULL OUTER JOIN (SELECT s_nationkey, count(*) AS s FROM supplier WHERE s_acctbal > 5000 GROUP BY s_nationkey) s ON s.s_nationkey = n.n_nationkey",
)


@query(
    "o_range_join",
    "SELECT c.c_custkey, count(*)::BIGINT AS near FROM customer c JOIN supplier s ON s.s_acctbal BETWEEN c.c_acctbal - 100 AND c.c_acctbal + 100 GROUP BY c.c_custkey",
)
def range_join(spark, d):
    """Cells of the range's width make it an equi-join with a residual test."""
    c = load(spark, d, "customer").select("c_custkey", "c_acctbal", F.explode(F.sequence(F.floor((F.col("c_acctbal") - 100) / 100), F.floor((F.col("c_acctbal") + 100) / 100))).alias("cell"))
    s = load(spark, d, "supplier").select("s_acctbal", F.floor(F.col("s_acctbal") / 100).alias("cell"))
    return c.join(s, "cell").filter(F.col("s_acctbal").between(F.col("c_acctbal") - 100, F.col("c_acctbal") + 100)).groupBy("c_custkey").agg(F.count("*").alias("near"))


@query(
    "o_asof",
    "SELECT p.event_id, max(c.event_id)::BIGINT AS before FROM events p JOIN events c ON c.user_id = p.user_id AND (c.ts, c.event_id) = (SELECT (x.ts, x.event_id) FROM events x WHERE x.event_type = 'click' AND x.user_id = p.user_id AND x.ts <= p.ts ORDER BY x.ts DESC, x.event_id DESC LIMIT 1) WHERE p.event_type = 'purchase' GROUP BY p.event_id",
)
def asof(spark, d):
    """For each purchase the user's latest click: one window over the union, and no range join."""
    rows = load(spark, d, "events").filter(F.col("event_type").isin("click", "purchase"))
    click = F.when(F.col("event_type") == "click", F.struct("ts", "event_id"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("c", F.max(click).over(w)).filter("event_type = 'purchase' AND c IS NOT NULL").select("event_id", F.col("c.event_id").alias("before"))


both("o_setops", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 INTERSECT SELECT p_partkey FROM part WHERE p_size > 20 EXCEPT SELECT l_partkey FROM lineitem WHERE l_discount > 0.09")
both(
    "o_windows",
    "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS prev, coalesce(lead(event_id) OVER w, -1) AS nxt, CAST(row_number() OVER w AS INTEGER) AS r, round(percent_rank() OVER w, 9) AS p, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
)


@query("o_json", "SELECT event_type, sum(json_extract_string(props, '$.k')::BIGINT)::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def json(spark, d):
    rows = load(spark, d, "events").withColumn("p", F.from_json("props", "k bigint"))
    return rows.groupBy("event_type").agg(F.sum("p.k").alias("k"), F.count("*").alias("n"))


@query(
    "o_dates",
    "SELECT date_trunc('month', ts) AS month, hour(ts)::INTEGER AS h, (dayofweek(ts) + 1)::INTEGER AS dow, count(*)::BIGINT AS n FROM events GROUP BY ALL",
)
def dates(spark, d):
    return load(spark, d, "events").groupBy(F.date_trunc("month", "ts").cast("timestamp_ntz").alias("month"), F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow")).agg(F.count("*").alias("n"))


@query("o_maps", "SELECT l_orderkey AS k, sum(l_linenumber)::BIGINT AS total, count(DISTINCT l_linenumber)::BIGINT AS n FROM lineitem GROUP BY l_orderkey")
def maps(spark, d):
    """Sums through a map of counts by line number: merged, transformed and folded again."""
    counts = load(spark, d, "lineitem").groupBy("l_orderkey", F.col("l_linenumber").cast("bigint").alias("x")).agg(F.count("*").alias("c"))
    m = counts.groupBy(F.col("l_orderkey").alias("k")).agg(F.map_from_entries(F.collect_list(F.struct("x", "c"))).alias("m"))
    weighted = F.map_values(F.transform_values("m", lambda k, v: k * v))
    return m.select("k", F.aggregate(weighted, F.lit(0).cast("bigint"), lambda s, x: s + x).alias("total"), F.size(F.map_keys("m")).cast("bigint").alias("n"))


@query("o_strings", "SELECT doc_id, length(text)::BIGINT AS n, (length(text) - length(replace(text, 'e', '')))::BIGINT AS e, upper(substr(lang, 1, 1)) || substr(lang, 2) AS lang, text LIKE '%licen%' AS lic FROM documents")
def strings(spark, d):
    return load(spark, d, "documents").select(
        "doc_id", F.length("text").cast("bigint").alias("n"), (F.length("text") - F.length(F.translate("text", "e", ""))).cast("bigint").alias("e"),
        F.initcap("lang").alias("lang"), F.col("text").like("%licen%").alias("lic"),
    )


_KL = draw(12, 0)


@query("o_udtf", sql.with_(sql.docs_sets() | sql.kl_members(2, 6, _KL), "SELECT id, s.l::INTEGER AS table_id, s.s AS sig FROM exploded WHERE s.s <> ''"))
def udtf(spark, d):
    sql_surface.register(spark)
    data.docs_sets(spark, d).filter("size(tokens) > 0").createOrReplaceTempView("doc_sets")
    return spark.sql("SELECT id, t.table_id, t.sig FROM doc_sets, LATERAL kl_expand(tokens, 2, 6, 0) t")


@query("o_udf", sql.with_(sql.docs_sets(), "SELECT id, " + " || ',' || ".join(f"({sql.minhash('tokens', draw(4, 8), i)})::VARCHAR" for i in range(4)) + " AS sig FROM sets WHERE len(tokens) > 0"))
def udf(spark, d):
    sql_surface.register(spark)
    data.docs_sets(spark, d).filter("size(tokens) > 0").createOrReplaceTempView("doc_sets")
    return spark.sql("SELECT id, array_join(minhash_sig(tokens, 4, 8), ',') AS sig FROM doc_sets")


@query("o_udaf", "SELECT label, list_avg(list(embedding[1]::DOUBLE)) > 0 AS first_positive, count(*)::BIGINT AS n FROM embeddings GROUP BY label")
def udaf(spark, d):
    rows = load(spark, d, "embeddings")
    means = rows.groupBy("label").agg(F.pandas_udf(sql_surface.vec_mean, "array<double>")("embedding").alias("v"))
    sizes = rows.groupBy("label").agg(F.count("*").alias("n"))
    return means.join(sizes, "label").select("label", (F.col("v")[0] > 0).alias("first_positive"), "n")


@query("o_regression", "SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem GROUP BY l_returnflag")
def regression(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("r")
    )


@query(
    "o_scalars",
    "SELECT o_orderkey, round(log2(o_totalprice), 6) AS bits, sign(o_totalprice - 150000)::DOUBLE AS side, levenshtein(o_orderpriority, '5-LOW')::INTEGER AS edits, "
    "date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, date_diff('month', DATE '1992-01-01', date_trunc('month', o_orderdate)::DATE)::DOUBLE AS months, "
    "o_orderkey % 7 > 0 AND o_custkey % 7 > 0 AS no_seventh, (CASE WHEN o_orderkey % 2 = 1 THEN o_orderkey ELSE 0 END + o_custkey + o_orderkey)::BIGINT AS merged, "
    "'{\"s\":\"' || o_orderstatus || '\",\"k\":' || o_orderkey || '}' AS js, 'STRUCT<k: BIGINT>' AS shape FROM orders",
)
def scalars(spark, d):
    """Functions that no other query uses: on numbers, strings, dates, arrays, maps and JSON."""
    day = F.col("o_orderdate").cast("date")
    first = F.lit("1992-01-01").cast("date")
    odd = F.map_filter(F.create_map(F.lit("a"), F.col("o_orderkey")), lambda k, v: v % 2 == 1)
    both = F.map_zip_with(
        F.create_map(F.lit("a"), F.col("o_custkey")), F.create_map(F.lit("a"), F.col("o_orderkey")), lambda k, x, y: x + y
    )
    return load(spark, d, "orders").select(
        "o_orderkey",
        F.round(F.log2("o_totalprice"), 6).alias("bits"),
        F.signum(F.col("o_totalprice") - 150000).alias("side"),
        F.levenshtein("o_orderpriority", F.lit("5-LOW")).alias("edits"),
        F.datediff(day, first).alias("days"),
        F.months_between(F.trunc(day, "month"), first).alias("months"),
        F.forall(F.array("o_orderkey", "o_custkey"), lambda x: x % 7 > 0).alias("no_seventh"),
        (F.coalesce(F.get(F.map_values(odd), F.lit(0)), F.lit(0)) + F.get(F.map_values(both), F.lit(0))).cast("bigint").alias("merged"),
        F.to_json(F.struct(F.col("o_orderstatus").alias("s"), F.col("o_orderkey").alias("k"))).alias("js"),
        F.schema_of_json(F.lit('{"k": 1}')).alias("shape"),
    )


_TUMBLE = "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL"


def _events(spark, d):
    """The events as a file stream: a folder of their own, as a table may be one file."""
    rows = load(spark, d, "events")
    return scoring.read_stream(spark, stage_folder(rows, "events"), rows.schema, "ts")


def _drain(spark, stream, name, mode="complete"):
    return scoring.drained(stream, spark, f"{name}_{uuid.uuid4().hex[:8]}", mode)


@query("st_tumbling", _TUMBLE)
def tumbling(spark, d):
    out = _drain(spark, scoring.windowed(_events(spark, d), "ts", "event_type", "1 hour"), "tumbling")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query(
    "st_sliding",
    "SELECT s AS start, event_type, count(*)::BIGINT AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL '30 minutes', ts), time_bucket(INTERVAL '30 minutes', ts) - INTERVAL '30 minutes']) AS s FROM events) GROUP BY ALL",
)
def sliding(spark, d):
    out = _drain(spark, scoring.windowed(_events(spark, d), "ts", "event_type", "1 hour", "30 minutes"), "sliding")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query(
    "st_session",
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k",
)
def session(spark, d):
    """Closed sessions are appended to files: there are about as many as events, too many for the driver.

    A session closes when the watermark passes it, so a row without user follows a day after the last event.
    """
    rows = load(spark, d, "events").select("user_id", "ts")
    last = rows.agg(F.max("ts").alias("ts")).filter("ts IS NOT NULL").select(
        F.lit(None).cast(rows.schema["user_id"].dataType).alias("user_id"), (F.col("ts") + F.expr("INTERVAL 1 DAY")).alias("ts")
    )
    rows = rows.unionByName(last)
    stream = scoring.read_stream(spark, stage_folder(rows, "events"), rows.schema, "ts", files=None)
    out = _drain(spark, scoring.sessions(stream, "ts", "user_id", "30 minutes"), "session", "append")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("st_dedup")
def dedup(spark, d):
    return _drain(spark, scoring.deduplicated(_events(spark, d), "ts", ["user_id", "event_type"], "1 day").select("event_id", "user_id"), "dedup", "append")


@query("st_drift")
def drift(spark, d):
    return _drain(spark, scoring.drift(_events(spark, d), "event_type", "value", 10.0), "drift", "update")


@query("st_assign")
def assign(spark, d):
    """Embeddings as a file stream, scored by seeded centers: the figures of the stream's clusters."""
    from bucketseed.experiments.phases import embedding_centers
    from bucketseed.functions.features import fixed_point
    from bucketseed.operators.assign import collected

    ids, vectors = collected(embedding_centers(spark, d), "vec")
    rows = load(spark, d, "embeddings")
    stream = scoring.read_stream(spark, stage_folder(rows, "embeddings"), rows.schema).select(
        F.col("vec_id").alias("id"), fixed_point("embedding").alias("vec")
    )
    return radii(_drain(spark, scoring.assign_stream(stream, ids, vectors), "assign", "append"))


@query(
    "st_interval_join",
    "SELECT b.event_id, a.ts AS click_ts FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL '2 hours' WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
)
def interval_join(spark, d):
    clicks = _events(spark, d).filter("event_type = 'click'").select("user_id", F.col("ts").alias("click_ts"))
    buys = _events(spark, d).filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("buy_ts"), "event_id")
    joined = scoring.interval_join(clicks, buys, "user_id", "click_ts", "buy_ts", "2 hours")
    out = _drain(spark, joined.select("b.event_id", "a.click_ts"), "interval", "append")
    return out.select("event_id", F.col("click_ts").cast("timestamp_ntz").alias("click_ts"))
