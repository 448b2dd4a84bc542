"""Feature builders: vectors, fixed point, token sets, record tokens, and row ids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.operators.ranking import ranked

LETTERS = "abcdefghijklmnopqrstuvwxyz"
FIXED = 1_000_000


def token_id(word: Column) -> Column:
    """28 bits of md5: small enough for affine permutations, the same in other engines."""
    return F.conv(F.substring(F.md5(word), 1, 7), 16, 10).cast("bigint")


def bound(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once: lambdas compute an expression at each use."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def word_set(text: Column | str) -> Column:
    """Sorted distinct ids of the words of lower-cased text; empty for null."""
    col = F.col(text) if isinstance(text, str) else text
    words = F.array_distinct(F.split(F.lower(F.coalesce(col, F.lit(""))), r"\s+"))
    return F.sort_array(F.array_distinct(F.transform(F.array_remove(words, ""), token_id)))


def shingle_set(text: Column | str, k: int = 5) -> Column:
    """Sorted distinct ids of the k-character runs of lower-cased text."""
    col = F.lower(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))
    runs = lambda c: F.when(
        F.size(c) >= k,
        F.transform(F.sequence(F.lit(0), F.size(c) - k), lambda i: F.concat(*[F.get(c, i + j) for j in range(k)])),
    ).otherwise(F.array(F.array_join(c, "")))
    grams = bound(F.split(col, ""), runs)
    return F.sort_array(F.array_distinct(F.transform(grams, token_id)))


def letter_histogram(text: Column | str) -> Column:
    """26 letter counts of lower-cased text (bigint)."""
    col = F.lower(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))
    return F.array(*[(F.length(col) - F.length(F.replace(col, F.lit(c), F.lit("")))).cast("bigint") for c in LETTERS])


def letter_shares(text: Column | str, scale: int = FIXED) -> Column:
    """Letter shares in fixed point; zeros for a text without letters."""
    return bound(
        letter_histogram(text),
        lambda counts: bound(
            F.aggregate(counts, F.lit(0).cast("bigint"), lambda s, x: s + x),
            lambda n: F.transform(
                counts, lambda x: F.when(n > 0, F.floor(x * F.lit(float(scale)) / n)).otherwise(F.lit(0)).cast("bigint")
            ),
        ),
    )


def fixed_point(vec: Column | str, scale: int = FIXED) -> Column:
    """floor(x * scale + 1/2) as bigint: sums and dot products are exact in any order."""
    return F.transform(vec, lambda x: F.floor(x.cast("double") * F.lit(float(scale)) + F.lit(0.5)).cast("bigint"))


def vector(df: DataFrame, cols: list[str], scale: str | None = None) -> Column:
    """Columns as array<double>; ``minmax`` or ``z`` scales by one aggregation."""
    if scale is None:
        return F.array(*[F.col(c).cast("double") for c in cols])
    stats = df.agg(
        *[f(F.col(c).cast("double")).alias(f"{n}{i}") for i, c in enumerate(cols) for n, f in
          (("a", F.min if scale == "minmax" else F.avg), ("b", F.max if scale == "minmax" else F.stddev_pop))]
    ).first()
    out = []
    for i, c in enumerate(cols):
        low = float(stats[f"a{i}"] or 0.0)
        span = float(stats[f"b{i}"] or 0.0) - (low if scale == "minmax" else 0.0)
        out.append((F.col(c).cast("double") - F.lit(low)) / F.lit(span or 1.0))
    return F.array(*out)


def record_tokens(cols: list[str]) -> Column:
    """(attribute, value) tokens of fixed length; a null is a value of its own."""
    return F.array(
        *[token_id(F.concat_ws("=", F.lit(c), F.coalesce(F.col(c).cast("string"), F.lit("\u0000")))) for c in cols]
    )


def one_hot_tokens(cols: list[str]) -> Column:
    """Mixed wide rows as one sorted set; nulls are left out."""
    parts = [F.when(F.col(c).isNotNull(), token_id(F.concat_ws("=", F.lit(c), F.col(c).cast("string")))) for c in cols]
    return F.sort_array(F.array_distinct(F.filter(F.array(*parts), lambda x: x.isNotNull())))


def html_tokens(html: Column | str) -> Column:
    col = F.col(html) if isinstance(html, str) else html
    return word_set(F.regexp_replace(F.coalesce(col, F.lit("")), r"<[^>]*>", " "))


def html_links(html: Column | str) -> Column:
    col = F.col(html) if isinstance(html, str) else html
    return F.array_distinct(F.regexp_extract_all(F.coalesce(col, F.lit("")), F.lit('href="([^"]*)"'), 1))


def baskets(orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    """(id, tokens): the distinct parts each customer bought."""
    return (
        lineitem.select("l_orderkey", "l_partkey")
        .join(orders.select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("id")), "l_orderkey")
        .groupBy("id")
        .agg(F.sort_array(F.collect_set("l_partkey")).alias("tokens"))
    )


def json_field(col: Column | str, name: str) -> Column:
    return F.get_json_object(col, f"$.{name}")


def with_row_id(df: DataFrame, mode: str = "rank", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (default: all columns) and ``id``, the row's number from 1 by all columns.

    ``rank`` is one distributed sort; ``hash`` takes a hash of the row in one pass (no number).
    """
    keep = keep or df.columns
    if mode == "hash":
        return df.select(*keep, F.xxhash64(*df.columns).alias("id"))
    return ranked(df, df.columns, keep).select(*keep, (F.col("rank") + 1).alias("id"))


def validate(df: DataFrame, numeric: list[str] = (), sets: list[str] = ()) -> tuple[DataFrame, DataFrame]:
    """(good, rejects): numerics that are null or NaN and sets that are null are rejected."""
    bad = F.lit(False)
    for c in numeric:
        bad = bad | F.col(c).isNull() | F.isnan(F.col(c).cast("double"))
    for c in sets:
        bad = bad | F.col(c).isNull()
    return df.filter(~bad), df.filter(bad)
