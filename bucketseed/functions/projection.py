"""Random projections: exact on fixed-point integers, or in bulk by matrix products."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def gaussian(count: int, dims: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=(count, dims))


def cauchy(count: int, dims: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).standard_cauchy(size=(count, dims))


def integer_directions(count: int, dims: int, seed: int, scale: int = 1000) -> list[list[int]]:
    """Gaussian directions as integers, so that dot products of fixed-point vectors are exact."""
    return np.rint(gaussian(count, dims, seed) * scale).astype(int).tolist()


#: Dot products of up to this many terms are written out, so that they compile; longer ones loop.
UNROLLED = 16


def dot(vec: Column | str, direction: list) -> Column:
    kind = "bigint" if isinstance(direction[0], int) else "double"
    if len(direction) <= UNROLLED:
        col = F.col(vec) if isinstance(vec, str) else vec
        terms = [(F.get(col, F.lit(i)) * F.lit(x)).cast(kind) for i, x in enumerate(direction)]
        return sum(terms[1:], terms[0])
    return F.aggregate(
        F.zip_with(vec, F.array(*[F.lit(x) for x in direction]), lambda x, y: (x * y).cast(kind)),
        F.lit(0).cast(kind),
        lambda s, x: s + x,
    )


def project(df: DataFrame, vec: str, directions: list[list]) -> DataFrame:
    """(table_id, id, h) for each direction, by exact column arithmetic."""
    hs = F.array(*[dot(vec, d) for d in directions])
    return df.select("id", F.posexplode(hs).alias("table_id", "h"))


def project_bulk(df: DataFrame, vec: str, directions: np.ndarray) -> DataFrame:
    """(id, hs array<double>): one matrix product per Arrow batch."""
    at = df.sparkSession.sparkContext.broadcast(np.ascontiguousarray(directions.T))

    def run(batches):
        for batch in batches:
            n = batch.num_rows
            x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float)
            h = x.reshape(n, -1) @ at.value if n else np.zeros((0, at.value.shape[1]))
            offsets = pa.array(np.arange(n + 1, dtype=np.int32) * h.shape[1])
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.ListArray.from_arrays(offsets, pa.array(h.ravel()))], ["id", "hs"]
            )

    rows = df.select("id", F.col(vec).alias("vec"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, hs array<double>")


def width_key(vec: Column | str, direction: list, offset: float, width: float) -> Column:
    """floor((a.x + b) / w): the bucket of fixed width."""
    return F.floor((dot(vec, direction) + F.lit(offset)) / F.lit(width))
