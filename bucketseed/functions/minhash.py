"""MinHash of sets in a row or in long form, K-signatures, and similarity estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.functions.permutations import Permutations


def minhash(tokens: Column | str, perms: Permutations, i: int) -> Column:
    """Least permuted token; null for an empty set."""
    col = F.col(tokens) if isinstance(tokens, str) else tokens
    return F.array_min(F.transform(col, lambda x: perms.of(x, i)))


def minhash_values(tokens: Column | str, perms: Permutations) -> Column:
    return F.array(*[minhash(tokens, perms, i) for i in range(len(perms))])


def minhash_long(df: DataFrame, set_col: str, member: str, perms: Permutations) -> DataFrame:
    """(set_col, size, h0, h1, ...): minima by partial aggregation, for sets of any size."""
    return df.groupBy(set_col).agg(
        F.count("*").alias("size"),
        *[F.min(perms.of(F.col(member), i)).alias(f"h{i}") for i in range(len(perms))],
    )


def signature(values: list[Column], mode: str = "text") -> Column:
    """K values as one key: exact text, or a compact 64-bit hash."""
    if mode == "text":
        return F.concat_ws("_", *[v.cast("string") for v in values])
    return F.xxhash64(*values)


def kl_signatures(values: Column, K: int, L: int, mode: str = "text") -> Column:
    """Array of struct(table_id, sig) from K * L values, K to each table."""
    return F.array(
        *[
            F.struct(
                F.lit(l).alias("table_id"),
                signature([F.get(values, l * K + k) for k in range(K)], mode).alias("sig"),
            )
            for l in range(L)
        ]
    )


def estimate_jaccard(a: Column | str, b: Column | str) -> Column:
    """Share of equal positions of two MinHash arrays."""
    equal = F.zip_with(a, b, lambda x, y: (x == y).cast("double"))
    return F.aggregate(equal, F.lit(0.0), lambda s, x: s + x) / F.size(equal)


def estimate_angle(a: Column | str, b: Column | str) -> Column:
    """Angle in radians from the share of differing hyperplane bits."""
    return F.lit(3.141592653589793) * (1 - estimate_jaccard(a, b))
