"""Phase 1: rows to buckets. Every kind of data ends as ``members(bucket_id, table_id, id)``.

Buckets stay in long form: only ids move, and no bucket is ever one array.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.functions.doph import doph, doph_column
from bucketseed.functions.features import token_id
from bucketseed.functions.minhash import kl_signatures, minhash_values
from bucketseed.functions.permutations import draw
from bucketseed.functions.projection import dot, integer_directions, width_key
from bucketseed.operators.ranking import ranked
from bucketseed.staging import staged


@dataclass(frozen=True)
class DatasetSpec:
    """What kind of rows a table holds; checked once against its schema."""

    kind: str  # dense, hetero, categorical, sparse
    id_col: str = "id"
    vec_col: str | None = None
    tokens_col: str | None = None
    numeric: tuple[str, ...] = ()
    categorical: tuple[str, ...] = ()
    params: dict = field(default_factory=dict)

    def check(self, df: DataFrame) -> DatasetSpec:
        need = [self.id_col, *filter(None, (self.vec_col, self.tokens_col)), *self.numeric, *self.categorical]
        missing = [c for c in need if c not in df.columns]
        if missing:
            raise ValueError(f"columns not found: {missing}")
        if self.kind not in ("dense", "hetero", "categorical", "sparse"):
            raise ValueError(f"unknown kind {self.kind}")
        return self


def bucket_key(table: Column, key: Column, mode: str = "text") -> Column:
    if mode == "text":
        return F.concat_ws(":", table.cast("string"), key.cast("string"))
    return F.xxhash64(table, key)


def rank_cut(projected: DataFrame, t: int, mode: str = "ranked", eps: float = 0.001) -> DataFrame:
    """Cut each table's (id, h) into ``t`` parts of equal count, ties by id.

    ``ranked`` is one range-partitioned sort and counts of its ranges; ``window`` gives the same parts
    with a whole table in one task, for comparison; ``quantile`` cuts at sketched quantiles in one scan.
    """
    if mode == "window":
        part = F.ntile(t).over(Window.partitionBy("table_id").orderBy("h", "id"))
        cut = projected.select("table_id", "id", (part - 1).alias("part"))
    elif mode == "ranked":
        cut = _ranked(projected, t)
    elif mode == "quantile":
        cut = _quantile(projected, t, eps)
    else:
        raise ValueError(mode)
    return cut.select(bucket_key(F.col("table_id"), F.col("part")).alias("bucket_id"), "table_id", "id")


def _ntile(t: int) -> Column:
    """ntile's part, from 0, of a row by its ``rank`` among ``total``."""
    rank, small, large = F.col("rank"), F.floor(F.col("total") / t), F.col("total") % t
    edge = large * (small + 1)
    return F.when(rank < edge, F.floor(rank / (small + 1))).otherwise(
        large + F.floor((rank - edge) / F.greatest(small, F.lit(1)))
    ).cast("int")


def _ranked(projected: DataFrame, t: int) -> DataFrame:
    return ranked(projected, ["h", "id"], ["id"], ["table_id"]).select("table_id", "id", _ntile(t).alias("part"))


def _quantile(projected: DataFrame, t: int, eps: float) -> DataFrame:
    shares = F.array(*[F.lit(i / t) for i in range(1, t)])
    cuts = projected.groupBy("table_id").agg(F.percentile_approx("h", shares, int(1 / eps)).alias("cuts"))
    part = F.size(F.filter("cuts", lambda c: c < F.col("h")))
    return projected.join(F.broadcast(cuts), "table_id").select("table_id", "id", part.alias("part"))


def transform_dense(df: DataFrame, vec: str, m: int, t: int, seed: int = 0, mode: str = "ranked", directions=None) -> DataFrame:
    """m projections, each cut into t parts: every id is in m buckets, one of each table."""
    if directions is None:
        dims = len(df.select(vec).first()[0])
        directions = integer_directions(m, dims, seed)
    hs = F.array(*[dot(vec, d) for d in directions])
    # projected once: the range sort reads its input twice
    rows = staged(df.select("id", hs.alias("hs")), "projected")
    return rank_cut(rows.select("id", F.posexplode("hs").alias("table_id", "h")), t, mode)


def width_buckets(df: DataFrame, vec: str, directions: list, offsets: list[float], width: float) -> DataFrame:
    """Buckets floor((a.x + b) / w): the fixed-width variant, whose w is hard to choose."""
    keys = F.array(*[width_key(vec, d, b, width) for d, b in zip(directions, offsets, strict=True)])
    return df.select("id", F.posexplode(keys).alias("table_id", "key")).select(
        bucket_key(F.col("table_id"), F.col("key")).alias("bucket_id"), "table_id", "id"
    )


def centered_buckets(df: DataFrame, vec: str, directions: list, width: float) -> DataFrame:
    """For each object and table, all ids within w/2 of its projection: overlapping, for ablation.

    The range join is an equi-join on cells of width w/2 and a residual test.
    """
    hs = F.array(*[dot(vec, d) for d in directions])
    rows = df.select("id", F.posexplode(hs).alias("table_id", "h")).withColumn("cell", F.floor(F.col("h") / (width / 2)))
    near = rows.select(
        F.col("id").alias("center"), "table_id", F.col("h").alias("ch"),
        F.explode(F.sequence(F.col("cell") - 1, F.col("cell") + 1)).alias("cell"),
    )
    return (
        near.join(rows, ["table_id", "cell"])
        .filter(F.abs(F.col("h") - F.col("ch")) <= width / 2)
        .select(bucket_key(F.col("table_id"), F.col("center")).alias("bucket_id"), "table_id", "id")
    )


def kl_buckets(df: DataFrame, tokens: str, K: int, L: int, seed: int = 0, mode: str = "text", perms=None) -> DataFrame:
    """L tables keyed by K-signatures: every id is in L buckets."""
    perms = perms or draw(K * L, seed)
    sigs = kl_signatures(minhash_values(tokens, perms), K, L, mode)
    return df.select("id", F.explode(sigs).alias("s")).select(
        bucket_key(F.col("s.table_id"), F.col("s.sig"), mode).alias("bucket_id"), F.col("s.table_id").alias("table_id"), "id"
    )


def discretise(df: DataFrame, numeric: list[str], bins: int, tie: str = "split", mode: str = "ranked") -> DataFrame:
    """Each numeric column as its rank part, 0 to bins - 1; ``tie='together'`` keeps equal values in one.

    ``ranked`` sorts all columns in one range-partitioned sort; ``window`` gives the same parts with a
    whole column in one task, for comparison; ``quantile`` cuts at sketched quantiles.
    """
    if mode == "ranked":
        cells = F.posexplode(F.array(*[F.col(c).cast("double") for c in numeric]))
        rows = staged(df.select("id", *numeric), "numeric").select("id", cells.alias("table_id", "h"))
        if tie == "split":
            parts = _ranked(rows, bins)
        else:
            placed = ranked(rows, ["h", "id"], ["id", "h"], ["table_id"])
            first = placed.groupBy("table_id", "h").agg(F.min("rank").alias("rank"), F.max("total").alias("total"))
            share = F.when(F.col("total") > 1, F.col("rank") / (F.col("total") - 1)).otherwise(0.0)
            parts = (
                placed.select("table_id", "id", "h")
                .join(first.withColumnRenamed("h", "_h").withColumnRenamed("table_id", "_t"), (F.col("table_id") == F.col("_t")) & F.col("h").eqNullSafe(F.col("_h")))
                .select("table_id", "id", F.least(F.floor(share * bins), F.lit(bins - 1)).cast("int").alias("part"))
            )
        wide = parts.groupBy("id").agg(*[F.max(F.when(F.col("table_id") == i, F.col("part"))).alias(f"_{c}") for i, c in enumerate(numeric)])
        return df.join(wide, "id").select(*[F.col(f"_{c}").alias(c) if c in numeric else F.col(c) for c in df.columns])
    if mode == "quantile":
        cuts = df.agg(
            *[F.percentile_approx(c, F.array(*[F.lit(i / bins) for i in range(1, bins)]), 10_000).alias(c) for c in numeric]
        ).first()
        for c in numeric:
            part = sum(((F.col(c) > F.lit(x)).cast("int") for x in sorted(set(cuts[c] or []))), F.lit(0))
            df = df.withColumn(c, part)
        return df
    for c in numeric:
        w = Window.orderBy(c, "id") if tie == "split" else Window.orderBy(c)
        part = F.ntile(bins).over(w) - 1 if tie == "split" else F.least(F.floor(F.percent_rank().over(w) * bins), F.lit(bins - 1)).cast("int")
        df = df.withColumn(f"_{c}", part)
    return df.select(*[F.col(f"_{c}").alias(c) if c in numeric else F.col(c) for c in df.columns if not (c.startswith("_") and c[1:] in numeric)])


def hetero_tokens(df: DataFrame, numeric: list[str], categorical: list[str], bins: int = 10, tie: str = "split", mode: str = "ranked") -> DataFrame:
    """(id, tokens): one (attribute, value) token for each attribute, numerics by rank part."""
    cut = discretise(df.select("id", *numeric, *categorical), numeric, bins, tie, mode) if numeric else df
    tokens = [
        token_id(F.concat_ws("=", F.lit(c), F.coalesce(F.col(c).cast("string"), F.lit("\u0000"))))
        for c in [*numeric, *categorical]
    ]
    return cut.select("id", F.array(*tokens).alias("tokens"))


def joint_tokens(df: DataFrame, numeric: list[str], categorical: list[str], m: int, t: int, seed: int = 0, directions=None) -> DataFrame:
    """The other reading: the numeric sub-vector's m part numbers are m categorical attributes."""
    directions = directions or integer_directions(m, len(numeric), seed)
    hs = F.array(*[dot(F.array(*[F.col(c) for c in numeric]), d) for d in directions])
    parts = _ranked(staged(df.select("id", hs.alias("hs")), "projected").select("id", F.posexplode("hs").alias("table_id", "h")), t)
    wide = parts.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("table_id", "part"))).alias("ps"))
    cats = [token_id(F.concat_ws("=", F.lit(c), F.coalesce(F.col(c).cast("string"), F.lit("\u0000")))) for c in categorical]
    named = F.transform("ps", lambda p: token_id(F.concat_ws("=", F.concat(F.lit("p"), p["table_id"].cast("string")), p["part"].cast("string"))))
    return df.join(wide, "id").select("id", F.concat(named, F.array(*cats)).alias("tokens"))


def transform_hetero(df: DataFrame, numeric, categorical, K: int, L: int, bins: int = 10, seed: int = 0, **options) -> DataFrame:
    return kl_buckets(hetero_tokens(df, list(numeric), list(categorical), bins, **options), "tokens", K, L, seed)


def transform_sparse(df: DataFrame, tokens: str, K: int, L: int, D: int | None = 400, seed: int = 0, exact: bool = False, densify: str = "rotation") -> DataFrame:
    """Densify to D coordinates, then bucket the set of (coordinate, value) tokens.

    ``D=None`` buckets the sets themselves; ``exact=True`` uses the column form (small D).
    """
    if D is None:
        return kl_buckets(df, tokens, K, L, seed)
    coords = df.select("id", doph_column(tokens, D, seed).alias("coords")) if exact else doph(df, tokens, D, seed, densify)
    return kl_buckets(coords.select("id", coordinate_tokens("coords").alias("tokens")), "tokens", K, L, seed + 1)


def coordinate_tokens(coords: str) -> Column:
    """(coordinate, value) pairs as tokens below the affine prime."""
    return F.transform(coords, lambda v, i: (v * 521 + i * 7919) % 268435399)


def to_buckets(df: DataFrame, spec: DatasetSpec, **params) -> DataFrame:
    """Dispatch on the declared kind to the one ``members`` schema."""
    spec.check(df)
    rows = df if spec.id_col == "id" else df.withColumnRenamed(spec.id_col, "id")
    options = {**spec.params, **params}
    if spec.kind == "dense":
        return transform_dense(rows, spec.vec_col, **options)
    if spec.kind == "sparse":
        return transform_sparse(rows, spec.tokens_col, **options)
    numeric = spec.numeric if spec.kind == "hetero" else ()
    return transform_hetero(rows, numeric, spec.categorical, **options)


def synchronised(members: DataFrame, sync: str = "by_bucket", workers: int | None = None) -> DataFrame:
    """Bring a bucket's rows together: whole tables to a worker, or buckets spread evenly."""
    key = "table_id" if sync == "by_table" else "bucket_id"
    return members.repartition(workers, key) if workers else members.repartition(key)


def bucket_stats(members: DataFrame) -> DataFrame:
    """One row: n_buckets, n_members, mean_size, max_size, singletons."""
    sizes = members.groupBy("bucket_id").agg(F.count("*").alias("n"))
    return sizes.agg(
        F.count("*").alias("n_buckets"),
        F.sum("n").alias("n_members"),
        (F.sum("n") / F.count("*")).alias("mean_size"),
        F.max("n").alias("max_size"),
        F.sum((F.col("n") == 1).cast("bigint")).alias("singletons"),
    )
