"""Densified one-permutation hashing: a set of any size becomes D coordinates.

One permutation spreads the tokens over D equal ranges of [0, PRIME); each range keeps its least
value, and an empty range borrows: ``rotation`` from the next range that has one (around the end),
``optimal`` from the first full range in an order of its own that all rows share. An empty set
gives D times -1.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.functions.features import bound
from bucketseed.functions.permutations import PRIME, affine_perms


def width_of(dims: int) -> int:
    return -(-PRIME // dims)


def orders(dims: int) -> np.ndarray:
    """For each range, every donor's place in its order."""
    rng = np.random.default_rng(20)
    return np.argsort(rng.permuted(np.tile(np.arange(dims), (dims, 1)), axis=1), axis=1)


def reduce_set(tokens: np.ndarray, a: int, b: int, dims: int, donor: np.ndarray | None) -> np.ndarray:
    if not len(tokens):
        return np.full(dims, -1, np.int64)
    v = np.sort((tokens.astype(np.int64) * a + b) % PRIME)
    r = v // width_of(dims)
    at = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
    full, least = r[at], v[at]
    out = np.full(dims, -1, np.int64)
    out[full] = least
    empty = np.flatnonzero(out < 0)
    if len(empty):
        if donor is None:
            out[empty] = least[np.searchsorted(full, empty) % len(full)]
        else:
            out[empty] = least[donor[np.ix_(empty, full)].argmin(1)]
    return out


def doph(df: DataFrame, tokens: str = "tokens", dims: int = 400, seed: int = 0, densify: str = "rotation", keep: tuple = ()) -> DataFrame:
    """(id, *keep, coords array<bigint>) by Arrow batches; linear in the set and in D."""
    (a, b), donor = affine_perms(1, seed).params[0], None if densify == "rotation" else orders(dims)

    def run(batches):
        for batch in batches:
            col = batch.column("_tokens")
            rows = [np.asarray(x.as_py() or [], np.int64) for x in col]
            flat = np.concatenate([reduce_set(x, a, b, dims, donor) for x in rows]) if rows else np.zeros(0, np.int64)
            offsets = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * dims)
            yield pa.RecordBatch.from_arrays(
                [*[batch.column(c) for c in ("id", *keep)], pa.ListArray.from_arrays(offsets, pa.array(flat))], ["id", *keep, "coords"]
            )

    rows = df.select("id", *keep, F.col(tokens).alias("_tokens"))
    kinds = dict(rows.dtypes)
    return rows.mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in ("id", *keep)) + ", coords array<bigint>")


def doph_column(tokens: Column | str, dims: int, seed: int = 0) -> Column:
    """The rotation variant as a column, for small D: ranges are scanned, so it costs D * |set|."""
    perm, width = affine_perms(1, seed), width_of(dims)
    values = F.transform(tokens, lambda x: perm.of(x, 0))
    ranges = F.array_sort(F.transform(values, lambda v: F.struct(F.floor(v / width).alias("r"), v.alias("v"))))
    after = lambda rs, j: F.get(F.filter(rs, lambda s: s["r"] >= j), F.lit(0))["v"]
    return bound(
        ranges,
        lambda rs: F.transform(
            F.sequence(F.lit(0), F.lit(dims - 1)),
            lambda j: F.coalesce(after(rs, j), F.get(rs, F.lit(0))["v"], F.lit(-1).cast("bigint")),
        ),
    )
