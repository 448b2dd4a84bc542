"""Functions for SQL users: Arrow UDFs, an aggregate, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from bucketseed.functions.doph import reduce_set
from bucketseed.functions.permutations import PRIME, affine_perms


def minhash_values(tokens: np.ndarray, count: int, seed: int) -> list[int]:
    perms = np.array(affine_perms(count, seed).params, np.int64)
    if not len(tokens):
        return [PRIME] * count
    return ((tokens[None].astype(np.int64) * perms[:, :1] + perms[:, 1:]) % PRIME).min(1).tolist()


def minhash_sig(tokens: pd.Series, count: pd.Series, seed: pd.Series) -> pd.Series:
    return pd.Series([minhash_values(np.asarray(t), int(c), int(s)) for t, c, s in zip(tokens, count, seed, strict=True)])


def doph_reduce(tokens: pd.Series, dims: pd.Series, seed: pd.Series) -> pd.Series:
    return pd.Series(
        [reduce_set(np.asarray(t, np.int64), *affine_perms(1, int(s)).params[0], int(n), None) for t, n, s in zip(tokens, dims, seed, strict=True)]
    )


def gauss_project(vec: pd.Series, count: pd.Series, seed: pd.Series) -> pd.Series:
    if not len(vec):
        return pd.Series([], dtype=object)
    from bucketseed.functions.projection import gaussian

    x = np.stack(vec.to_numpy()).astype(float)
    return pd.Series(list(x @ gaussian(int(count.iloc[0]), x.shape[1], int(seed.iloc[0])).T))


def vec_mean(vec: pd.Series) -> list:
    """Aggregate: the mean vector of a group."""
    return np.stack(vec.to_numpy()).astype(float).mean(0).tolist()


def mode_vec(vec: pd.Series) -> list:
    """Aggregate: each coordinate's most frequent value, ties to the least."""
    out = []
    for col in np.stack(vec.to_numpy()).T:
        values, n = np.unique(col, return_counts=True)
        out.append(int(values[n.argmax()]))
    return out


#: Wrapped only where a session is there: workers import this module without one.
UDFS = {
    minhash_sig: "array<bigint>",
    doph_reduce: "array<bigint>",
    gauss_project: "array<double>",
    vec_mean: "array<double>",
    mode_vec: "array<bigint>",
}


class KlExpand:
    """Table function: a set's (table_id, signature) rows."""

    def eval(self, tokens: list, K: int, L: int, seed: int) -> Iterator[tuple]:
        h = minhash_values(np.asarray(tokens, np.int64), K * L, seed)
        for t in range(L):
            yield t, "_".join(str(x) for x in h[t * K : (t + 1) * K])


class ClusterTable:
    """Table function over TABLE(id, vec): k-means of a small table in one partition."""

    def __init__(self):
        self.rows = []

    def eval(self, row, k: int):
        self.k = k
        self.rows.append((row["id"], row["vec"]))

    def terminate(self):
        if not self.rows:
            return
        x = np.array([r[1] for r in self.rows], float)
        c = x[np.linspace(0, len(x) - 1, min(self.k, len(x))).astype(int)]
        for _ in range(10):
            who = ((x[:, None] - c[None]) ** 2).sum(-1).argmin(1)
            c = np.array([x[who == j].mean(0) if (who == j).any() else c[j] for j in range(len(c))])
        for (i, _), w in zip(self.rows, who, strict=True):
            yield int(i), int(w)


def nearest_center(ids: np.ndarray, centers: np.ndarray):
    """An iterator UDF bound to a model: the nearest center's id."""

    @F.pandas_udf("bigint")
    def near(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        c = centers.astype(float)
        for vec in batches:
            if not len(vec):
                yield pd.Series([], dtype="int64")
                continue
            x = np.stack(vec.to_numpy()).astype(float)
            yield pd.Series(ids[((x * x).sum(1)[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T).argmin(1)])

    return near


def register(spark: SparkSession) -> None:
    """minhash_sig, doph_reduce, gauss_project, vec_mean, mode_vec, kl_expand, cluster_table."""
    for fn, kind in UDFS.items():
        spark.udf.register(fn.__name__, F.pandas_udf(fn, kind))
    spark.udtf.register("kl_expand", F.udtf(KlExpand, returnType="table_id int, sig string"))
    spark.udtf.register("cluster_table", F.udtf(ClusterTable, returnType="id bigint, cluster_id bigint"))
