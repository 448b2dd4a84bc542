"""Mixing sources to target weights by Poisson replication.

Each source gets the mean repetition rate that brings its expected rows to its share of the total.
A document's count inverts the Poisson distribution at a number that a hash of (seed, id) gives, so
reruns and lost tasks give the same copies; means above ``PART`` are sums of parts with their own
numbers. Rows are exploded by their counts and put in a global order by hash. Column expressions
only; counts per source are the one aggregate.

Defined results: a null source is a source of its own; sources without a target keep the weight 1
if ``others`` is 1 (0 drops them, as asked by name only); repeated rows draw the same count each;
a null id hashes as the empty text; an empty table gives no rows; all columns are carried, and those
named copy, rate or shuffle_key are replaced; a source of weight 0 goes, and if all weigh 0 nothing
is left; a negative weight is an error; equal shuffle keys are ordered by id, then copy; texts are
moved whole, however long.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.staging import staged

PART = 16.0


def uniform(seed: int, *cols: Column) -> Column:
    """52 bits of md5 as a number strictly between 0 and 1."""
    key = F.concat_ws(":", F.lit(str(seed)), *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    bits = F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("bigint")
    return (bits.cast("double") + 0.5) / F.lit(float(1 << 52))


def poisson_cdf(mean: Column) -> Column:
    """Cumulative probabilities of 0, 1, ... until less than 2^-53 is left (means up to PART)."""
    steps = F.ceil(mean + 9 * F.sqrt(mean) + 14).cast("int")
    start = F.struct(F.exp(-mean).alias("p"), F.exp(-mean).alias("c"), F.array(F.exp(-mean)).alias("all"))
    return F.aggregate(
        F.sequence(F.lit(1), steps),
        start,
        lambda a, i: F.struct(
            (a["p"] * mean / i).alias("p"),
            (a["c"] + a["p"] * mean / i).alias("c"),
            F.concat(a["all"], F.array(a["c"] + a["p"] * mean / i)).alias("all"),
        ),
        lambda a: a["all"],
    )


def invert_poisson(u: Column, cdf: Column) -> Column:
    """The least k whose cumulative probability reaches ``u``."""
    return F.size(F.filter(cdf, lambda c: c < u)).cast("bigint")


def mixing_rates(
    docs: DataFrame, weights: dict[str, float], others: float = 1.0, total: float | None = None
) -> DataFrame:
    """(_source, _rate, _whole, _cdf, _part_cdf): target share times ``total`` (default: all rows)
    over the source's rows; its whole PARTs, and the tables that invert the rest and one PART.
    """
    if others < 0 or any(float(w) < 0 for w in weights.values()):
        raise ValueError("weights must not be negative")
    named = F.create_map(*[F.lit(x) for k, v in weights.items() for x in (k, float(v))]) if weights else None
    weight = F.coalesce(named[F.col("_source")], F.lit(others)) if weights else F.lit(others)
    counts = (
        docs.groupBy(F.col("source").cast("string").alias("_source"))
        .agg(F.count("*").alias("_n"))
        .withColumn("_w", weight)
    )
    sums = counts.agg(F.sum("_w").alias("_sw"), F.sum("_n").alias("_sn"))
    goal = F.col("_sn").cast("double") if total is None else F.lit(float(total))
    return (
        counts.crossJoin(F.broadcast(sums))  # one row
        .filter("_w > 0")
        .select("_source", (F.col("_w") / F.col("_sw") * goal / F.col("_n")).alias("_rate"))
        .withColumn("_whole", F.floor(F.col("_rate") / PART).cast("int"))
        .withColumn("_rest", F.col("_rate") - F.col("_whole") * PART)
        .withColumns({"_cdf": poisson_cdf(F.col("_rest")), "_part_cdf": poisson_cdf(F.lit(PART))})
    )


def replicate(
    docs: DataFrame,
    weights: dict[str, float],
    others: float = 1.0,
    total: float | None = None,
    seed: int = 42,
    id_col: str = "doc_id",
    shuffled: bool = True,
) -> DataFrame:
    """All columns of ``docs`` plus copy (from 0), rate and shuffle_key; rows in global hash order."""
    rates = mixing_rates(docs, weights, others, total)
    names = [c for c in docs.columns if c not in ("copy", "rate", "shuffle_key")]
    parts = F.when(
        F.col("_whole") >= 1,
        F.aggregate(
            F.transform(
                F.sequence(F.lit(1), F.col("_whole")),
                # the array binds the number, which a lambda would compute anew at each step
                lambda i: F.get(
                    F.transform(
                        F.array(uniform(seed, F.col(id_col), i)), lambda u: invert_poisson(u, F.col("_part_cdf"))
                    ),
                    F.lit(0),
                ),
            ),
            F.lit(0).cast("bigint"),
            lambda a, x: a + x,
        ),
    ).otherwise(F.lit(0).cast("bigint"))
    slim = docs.select(*names)
    counted = (
        slim.join(rates, slim["source"].cast("string").eqNullSafe(F.col("_source")))
        .withColumn("_u", uniform(seed, F.col(id_col)))
        .withColumn("_count", invert_poisson(F.col("_u"), F.col("_cdf")) + parts)
        .filter("_count > 0")
    )
    copies = counted.select(
        *names,
        F.col("_rate").alias("rate"),
        F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("_count") - 1)).alias("copy"),
    ).withColumn("shuffle_key", uniform(seed + 1, F.col(id_col), F.col("copy")))
    return copies.orderBy("shuffle_key", id_col, "copy") if shuffled else copies


#: Production weights of the query: the hot source is halved against the others, one is doubled.
WEIGHTS = {"src0": 0.5, "src1": 2.0}


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    # whole documents are repeated and moved; the columns that SQL knows are read from the result
    mixed = staged(replicate(load(spark, sf_dir, "documents"), WEIGHTS), "mixed")
    return mixed.select("doc_id", "source", "rate", "copy", "shuffle_key").orderBy("shuffle_key", "doc_id", "copy")


_U = "((('0x' || substr(md5({key}), 1, 13))::BIGINT)::DOUBLE + 0.5) / 4503599627370496.0"

ORACLE = f"""
WITH RECURSIVE n AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
w AS (SELECT *, CASE source WHEN 'src0' THEN 0.5::DOUBLE WHEN 'src1' THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS w FROM n),
r AS (SELECT source, w / sum(w) OVER () * (sum(n) OVER ())::DOUBLE / n AS rate FROM w),
d AS (SELECT doc_id, source, rate, {_U.format(key="'42:' || doc_id")} AS u FROM documents JOIN r USING (source)),
p AS (
  SELECT doc_id, source, rate, u, exp(-rate) AS p, exp(-rate) AS c, 0::BIGINT AS k FROM d
  UNION ALL
  SELECT doc_id, source, rate, u, p * rate / (k + 1), c + p * rate / (k + 1), k + 1 FROM p WHERE c < u AND k < 80
), m AS (SELECT doc_id, source, rate, max(k) AS k FROM p GROUP BY ALL),
x AS (SELECT doc_id, source, rate, unnest(range(0, k)) AS copy FROM m WHERE k > 0)
SELECT doc_id, source, rate, copy, {_U.format(key="'43:' || doc_id || ':' || copy")} AS shuffle_key FROM x
"""
