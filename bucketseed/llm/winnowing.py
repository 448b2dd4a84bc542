"""Benchmark decontamination by winnowing: shared fingerprints, then extended hits.

A k-gram hash is a fingerprint if it is the minimum of some run of ``window - k + 1`` neighbouring
k-gram hashes; two texts that share ``window`` words in a row thus share a fingerprint. Documents
with a fingerprint of a test item are candidates; from every k-gram that a candidate shares with
the items' fingerprints, hits are extended to whole windows, in words to either side. Items of
fewer words than a window are looked up by grams of their own length, as no sampling can promise
them. Column expressions only; nothing is emitted per pair of documents.

Defined results: null or empty text has no words and no hit; an item without words never occurs;
repeated ``item_id`` rows count once; every row of documents is judged by its own text, whatever its
``doc_id`` (repeated, null, of any type); texts are read whole, however long; extra columns are
carried; an empty table gives no rows, and without items nothing is hit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.columns import NOT_ALNUM, NOT_ALNUM_CASED, ascii_lower, gram_hashes, pieces
from bucketseed.staging import staged

#: A side is broadcast only if its rows were counted and are no more than this (about 80 bytes each).
BROADCAST_ROWS = 200_000


def _word_hashes(text: str) -> Column:
    return F.transform(pieces(ascii_lower(F.col(text)), NOT_ALNUM), lambda w: F.xxhash64(w))


def _minima(grams: Column, run: int) -> Column:
    last = F.size(grams) - run
    return F.when(
        last >= 0,
        F.array_distinct(
            F.transform(
                F.sequence(F.lit(0), last),
                lambda i: F.least(*[F.get(grams, i + k) for k in range(run)]),
            )
        ),
    ).otherwise(F.array().cast("array<bigint>"))


def _sized(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def _around(windows: Column, i: Column, reach: int) -> Column:
    """Hashes of the windows that hold the k-gram at ``i``, by how far before it they start."""
    return F.array(*[F.when(i >= s, F.get(windows, i - s)) for s in range(reach)])


def _placed_grams(words: Column, length: int) -> Column:
    return F.transform(
        gram_hashes(words, length),
        lambda g, i: F.struct(F.lit(length).alias("length"), i.alias("start"), g.alias("_g")),
    )


def find_hits(
    docs: DataFrame, items: DataFrame, text: str = "text", window: int = 10, k: int = 5, key: str = "doc_id"
) -> DataFrame:
    """Distinct (``key``, start, length, item_id): where windows of items occur, in words.

    Rows that share a value of ``key`` share their findings; ``_keyed`` gives rows a key of their own.
    """
    run = window - k + 1
    item_words = (
        items.select("item_id", _word_hashes(text).alias("_w"))
        .withColumn("_n", F.size("_w"))
        .filter("_n > 0")
    )
    item_grams = (
        item_words.filter(F.col("_n") >= window)
        .withColumns({"_k": gram_hashes(F.col("_w"), k), "_win": gram_hashes(F.col("_w"), window)})
        .withColumn("_min", _minima(F.col("_k"), run))
        .select(
            "item_id",
            "_min",
            F.explode(
                F.transform(
                    "_k",
                    lambda g, i: F.struct(g.alias("k"), _around(F.col("_win"), i, run).alias("win")),
                )
            ).alias("_e"),
        )
        .filter(F.array_contains("_min", F.col("_e.k")))
        .select("item_id", F.col("_e.k").alias("_fp"), F.col("_e.win").alias("_iwin"))
        .distinct()
    )
    prints = item_grams.select("_fp").distinct()
    sizes = item_grams.agg(F.count("*").alias("a"), F.count_distinct("_fp").alias("b")).first()
    words = docs.select(key, _word_hashes(text).alias("_w"))
    candidates = staged(
        words.withColumn("_k", gram_hashes(F.col("_w"), k)).select(key, F.explode(_minima(F.col("_k"), run)).alias("_fp"))
        .join(_sized(prints, sizes["b"]), "_fp", "left_semi")
        .select(F.col(key).alias("_cand"))
        .distinct(),
        "candidates",
    )
    # Texts move, if anything does, and not their several times larger hashes.
    chosen = docs.select(key, F.col(text).alias("_text")).join(
        _sized(candidates, candidates.count()), F.col(key).eqNullSafe(F.col("_cand")), "left_semi"
    )
    extended = (
        chosen.select(key, _word_hashes("_text").alias("_w"))
        .withColumns({"_k": gram_hashes(F.col("_w"), k), "_win": gram_hashes(F.col("_w"), window)})
        .select(
            key,
            F.explode(
                F.transform(
                    "_k",
                    lambda g, i: F.struct(
                        g.alias("k"), i.alias("i"), _around(F.col("_win"), i, run).alias("win")
                    ),
                )
            ).alias("_e"),
        )
        .select(key, F.col("_e.k").alias("_fp"), F.col("_e.i").alias("_at"), "_e.win")
        .join(_sized(item_grams, sizes["a"]), "_fp")
        .select(
            key,
            "item_id",
            F.explode(
                F.filter(
                    F.transform(
                        F.arrays_zip("win", "_iwin"),
                        lambda p, s: F.when(p["win"] == p["_iwin"], F.col("_at") - s),
                    ),
                    lambda s: s.isNotNull(),
                )
            ).alias("start"),
        )
        .select(key, "start", F.lit(window).alias("length"), "item_id")
    )
    shorts = sorted(
        r["_n"] for r in item_words.filter(F.col("_n") < window).select("_n").distinct().collect()  # below window
    )
    if not shorts:
        return extended.distinct()
    own = staged(
        item_words.filter(F.col("_n") < window).select(
            "item_id",
            F.col("_n").alias("length"),
            F.coalesce(*[F.when(F.col("_n") == n, F.get(gram_hashes(F.col("_w"), n), F.lit(0))) for n in shorts]).alias("_g"),
        ),
        "short-items",
    )
    grams = F.flatten(F.array(*[_placed_grams(F.col("_w"), n) for n in shorts]))
    whole = (
        words.select(key, F.explode(grams).alias("_e"))
        .select(key, "_e.length", "_e.start", "_e._g")
        .join(_sized(own, own.count()), ["length", "_g"])
        .select(key, "start", "length", "item_id")
    )
    return extended.unionByName(whole).distinct()


def _keyed(docs: DataFrame) -> DataFrame:
    """``docs`` in a stage file, with a number of its own for each row."""
    return staged(docs.select("*", F.monotonically_increasing_id().alias("_row")), "rows")


def decontaminate(
    docs: DataFrame, items: DataFrame, text: str = "text", window: int = 10, k: int = 5
) -> DataFrame:
    """All columns of ``docs`` plus n_words, n_hit, n_items, item_ids, contaminated.

    A word inside any occurrence of an item's window is hit; it counts once.
    """
    rows = _keyed(docs)
    spans = (
        find_hits(rows, items, text, window, k, "_row")
        .groupBy(F.col("_row").alias("_hid"))
        .agg(
            F.collect_set(F.struct("start", "length")).alias("_spans"),
            F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("item_ids"),
        )
        .select(
            "_hid",
            "item_ids",
            F.size(
                F.array_distinct(
                    F.flatten(
                        F.transform(
                            "_spans", lambda s: F.sequence(s["start"], s["start"] + s["length"] - 1)
                        )
                    )
                )
            ).alias("_hit"),
        )
    )
    names = [c for c in docs.columns if c not in ("n_words", "n_hit", "n_items", "item_ids", "contaminated")]
    return (
        rows.select("_row", *names, F.size(pieces(F.col(text), NOT_ALNUM_CASED)).cast("bigint").alias("n_words"))
        .join(spans, F.col("_row") == F.col("_hid"), "left")
        .select(
            *names,
            "n_words",
            F.coalesce("_hit", F.lit(0)).cast("bigint").alias("n_hit"),
            F.coalesce(F.size("item_ids"), F.lit(0)).cast("bigint").alias("n_items"),
            F.coalesce("item_ids", F.array().cast("array<string>")).alias("item_ids"),
            F.col("_hit").isNotNull().alias("contaminated"),
        )
    )


def uncontaminated(docs: DataFrame, items: DataFrame, text: str = "text", window: int = 10, k: int = 5) -> DataFrame:
    """The rows of ``docs`` in which no window of an item occurs, with all their columns."""
    rows = _keyed(docs)
    hit = staged(find_hits(rows, items, text, window, k, "_row").select("_row").distinct(), "hits")
    return rows.join(_sized(hit, hit.count()), "_row", "left_anti").select(docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    docs, items = load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")
    return decontaminate(docs.select("doc_id", "text"), items).select(
        "doc_id",
        "n_words",
        "n_hit",
        "n_items",
        F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"),
        "contaminated",
    )


_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_RX = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

ORACLE = rf"""
WITH dw AS (SELECT doc_id, regexp_extract_all({_LOW}, '{_RX}') AS ws FROM documents),
iw AS (SELECT item_id, regexp_extract_all({_LOW}, '{_RX}') AS ws FROM benchmark),
il AS (SELECT item_id, ws, least(len(ws), 10) AS m FROM iw WHERE len(ws) > 0),
win AS (SELECT DISTINCT item_id, m, array_to_string(ws[i:i+m-1], ' ') AS k
        FROM (SELECT item_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS i FROM il)),
ms AS (SELECT DISTINCT m FROM win),
dg AS (SELECT doc_id, m, i, array_to_string(ws[i:i+m-1], ' ') AS k
       FROM (SELECT doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS i
             FROM dw, ms WHERE len(ws) >= m)),
hit AS (SELECT doc_id, dg.i, dg.m, item_id FROM dg JOIN win USING (m, k)),
pos AS (SELECT doc_id, count(DISTINCT p) AS n FROM
        (SELECT doc_id, unnest(range(i, i + m)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(DISTINCT item_id) AS n,
        string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids
        FROM hit GROUP BY doc_id)
SELECT dw.doc_id, len(ws)::BIGINT AS n_words, coalesce(pos.n, 0)::BIGINT AS n_hit,
  coalesce(its.n, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
  pos.n IS NOT NULL AS contaminated
FROM dw LEFT JOIN pos ON pos.doc_id = dw.doc_id LEFT JOIN its ON its.doc_id = dw.doc_id
"""
