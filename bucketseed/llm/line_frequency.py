"""Quality rules: lines that many documents of one host share are removed; what is left decides.

A line is normalised (lower case, digits and white space as one blank) and hashed. Its frequency
in a host is the number of documents of that host that hold it; with ``copies="once"`` documents
with the same text count as one. Lines above the host's limit are removed, and a document that
keeps too few of its words is rejected as depleted. Column expressions only.

Defined results: null text is an empty text and fails the base rules; a null host is a host of its
own; every row is a document, also one that repeats another; a line that repeats within a document
counts once; a line exactly at the limit stays; texts are read whole, however long; an empty table
gives no rows; extra columns are ignored unless carried.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.columns import SPACE, gram_hashes, pieces
from bucketseed.staging import staged

SEPARATORS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 8


def document_rules(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed."""
    words = docs.withColumn("_text", F.coalesce(F.col(text), F.lit(""))).withColumn(
        "_h", F.transform(pieces(F.col("_text"), SPACE), lambda w: F.xxhash64(w))
    )
    grams = words.withColumn("_g", gram_hashes(F.col("_h"), WINDOW)).withColumn(
        "_lines",
        F.filter(F.split("_text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")),
    )
    # Only texts with a repeated window pay for the sort that finds its places.
    ordered = grams.withColumn(
        "_o",
        F.when(
            F.size(F.array_distinct("_g")) < F.size("_g"),
            F.sort_array(F.transform("_g", lambda g, i: F.struct(g.alias("g"), i.alias("i")))),
        ),
    )
    starts = ordered.withColumn(
        "_s",
        F.sort_array(
            F.transform(
                F.filter(
                    "_o",
                    lambda x, i: F.coalesce(F.get("_o", i - 1)["g"] == x["g"], F.lit(False))
                    | F.coalesce(F.get("_o", i + 1)["g"] == x["g"], F.lit(False)),
                ),
                lambda x: x["i"],
            )
        ),
    )
    covered = F.aggregate(
        F.transform(
            "_s",
            lambda s, i: F.least(F.lit(WINDOW), F.coalesce(F.get("_s", i + 1) - s, F.lit(WINDOW))),
        ),
        F.lit(0).cast("bigint"),
        lambda a, x: a + x,
    )
    size = F.length("_text")
    measured = starts.withColumns(
        {
            "n_words": F.size("_h").cast("bigint"),
            "word_chars": F.length(F.translate("_text", SEPARATORS, "")).cast("bigint"),
            "n_symbols": (size - F.length(F.translate("_text", SYMBOLS, ""))).cast("bigint"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("bigint"),
            "n_repeat_words": F.coalesce(covered, F.lit(0)).cast("bigint"),
        }
    )
    return measured.withColumn(
        "base_failed",
        (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words")),
    ).drop("_h", "_g", "_o", "_s")


def line_frequency(
    docs: DataFrame,
    host: str = "source",
    text: str = "text",
    carry: tuple[str, ...] = ("doc_id",),
    min_docs: int = 10,
    max_share: float = 0.005,
    min_left: float = 0.3,
    min_words: int = 10,
    cleaned: bool = False,
    copies: str = "each",
) -> DataFrame:
    """One row per input row: ``carry``, the document rules, words_left, kept.

    A line goes when more than ``max(min_docs, max_share * documents of the host)`` documents of its host
    hold it. A document stays if it passes the document rules and keeps at least ``min_words``
    words and the share ``min_left`` of its words. ``cleaned=True`` adds ``cleaned_text``, the
    text without the lines that went.
    """
    slim = docs.select(
        *carry,
        F.col(host).cast("string").alias("_host"),
        F.col(text).alias("_raw"),
    )
    ruled = document_rules(slim, "_raw")
    lines = F.transform(
        F.col("_lines"),
        lambda x: F.struct(
            F.xxhash64(F.trim(F.lower(F.regexp_replace(x, r"[\x20\x09-\x0D0-9]+", " ")))).alias("h"),
            F.size(pieces(x, SPACE)).alias("n"),
            *([x.alias("line")] if cleaned else []),
        ),
    )
    rows = staged(
        ruled.select(
            F.monotonically_increasing_id().alias("_row"),
            *carry,
            "_host",
            *([F.xxhash64("_text").alias("_copy")] if copies == "once" else []),
            *"n_words word_chars n_symbols n_dup_lines n_repeat_words base_failed".split(),
            lines.alias("_lines"),
        ),
        "lines",
    )
    counted = rows.dropDuplicates(["_host", "_copy"]) if copies == "once" else rows
    hosts = counted.groupBy("_host").agg(F.count("*").alias("_texts"))
    spread = rows.select("_row", "_host", F.explode("_lines").alias("_line")).select(
        "_row", "_host", F.col("_line.h").alias("_h"), F.col("_line.n").alias("_n")
    )
    common = (
        counted.select("_host", F.explode(F.array_distinct(F.transform("_lines", lambda x: x["h"]))).alias("_h"))
        .groupBy("_host", "_h")
        .agg(F.count("*").alias("_df"))
        .filter(F.col("_df") > min_docs)
        .alias("c")
        .join(hosts.alias("t"), F.col("c._host").eqNullSafe(F.col("t._host")))
        .filter(F.col("_df") > max_share * F.col("_texts"))
        .select(F.col("c._host").alias("_chost"), F.col("_h").alias("_ch"))
    )
    gone = (
        spread.join(
            common, F.col("_host").eqNullSafe(F.col("_chost")) & (F.col("_h") == F.col("_ch"))
        )
        .groupBy("_row")
        .agg(F.sum("_n").alias("_gone"), F.collect_set("_h").alias("_cut"))
        .withColumnRenamed("_row", "_grow")
    )
    judged = (
        rows.join(gone, F.col("_row") == F.col("_grow"), "left")
        .withColumn("words_left", F.col("n_words") - F.coalesce("_gone", F.lit(0)))
        .withColumn(
            "kept",
            ~F.col("base_failed")
            & (F.col("words_left") >= min_words)
            & (F.col("words_left") >= min_left * F.col("n_words")),
        )
    )
    out = judged.select(
        *carry,
        *"n_words word_chars n_symbols n_dup_lines n_repeat_words base_failed words_left kept".split(),
        *(
            [
                F.array_join(
                    F.transform(
                        F.filter(
                            "_lines",
                            lambda x: ~F.coalesce(F.array_contains("_cut", x["h"]), F.lit(False)),
                        ),
                        lambda x: x["line"],
                    ),
                    "\n",
                ).alias("cleaned_text")
            ]
            if cleaned
            else []
        ),
    )
    return out


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    return line_frequency(load(spark, sf_dir, "documents"))


_W = r"[^\x20\x09-\x0D]+"

ORACLE = rf"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT *, regexp_extract_all(t, '{_W}') AS ws,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d
), g AS (
  SELECT r, i, array_to_string(ws[i:i+7], ' ') AS k
  FROM (SELECT r, ws, unnest(range(1, len(ws) - 6)) AS i FROM w WHERE len(ws) >= 8)
), rep AS (
  SELECT r, count(DISTINCT p) AS n FROM (
    SELECT r, unnest(range(i, i + 8)) AS p
    FROM (SELECT r, i, count(*) OVER (PARTITION BY r, k) AS c FROM g) WHERE c > 1) GROUP BY r
), ln AS (
  SELECT r, source, t, len(regexp_extract_all(x, '{_W}')) AS n,
         trim(lower(regexp_replace(x, '[\x20\x09-\x0D0-9]+', ' ', 'g')), ' ') AS k
  FROM (SELECT r, source, t, unnest(ls) AS x FROM w)
), hosts AS (SELECT source, count(*) AS texts FROM d GROUP BY source),
common AS (
  SELECT l.source, l.k FROM ln l JOIN hosts h USING (source)
  GROUP BY l.source, l.k, h.texts
  HAVING count(DISTINCT l.r) > 10 AND count(DISTINCT l.r) > 0.005 * h.texts
), gone AS (SELECT r, sum(n) AS n FROM ln JOIN common USING (source, k) GROUP BY r),
m AS (
  SELECT w.doc_id, len(ws) AS n_words,
    length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
    length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
    len(ls) - len(list_distinct(ls)) AS n_dup_lines,
    coalesce(rep.n, 0) AS n_repeat_words,
    len(ws) - coalesce(gone.n, 0) AS words_left
  FROM w LEFT JOIN rep ON rep.r = w.r LEFT JOIN gone ON gone.r = w.r
), b AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars,
  n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines,
  n_repeat_words::BIGINT AS n_repeat_words, base_failed, words_left::BIGINT AS words_left,
  NOT base_failed AND words_left >= 10 AND words_left >= 0.3 * n_words AS kept
FROM b
"""
