"""Distances as column expressions; ``distance(name)`` finds one by name."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _fold(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda s, x: s + x)


def l2(a, b) -> Column:
    return F.sqrt(_fold(F.zip_with(a, b, lambda x, y: ((x - y) * (x - y)).cast("double"))))


def l1(a, b) -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: F.abs(x - y).cast("double")))


def hamming(a, b) -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: (x != y).cast("double")))


def jaccard(a, b) -> Column:
    """1 - |a and b| / |a or b| of two sets; two empty sets are equal."""
    both = F.size(F.array_intersect(a, b))
    either = F.size(F.array_union(a, b))
    return F.when(either == 0, 0.0).otherwise(1 - both / either)


def jaccard_tokens(a, b) -> Column:
    """1 - M / (2d - M) for rows of d coordinates of which M are equal."""
    d, m = F.size(a), F.size(a) - hamming(a, b)
    return 1 - m / (2 * d - m)


def doph_estimate(a, b) -> Column:
    """1 - M / D: the estimate that densified coordinates give."""
    return hamming(a, b) / F.size(a)


def cosine(a, b) -> Column:
    dot = _fold(F.zip_with(a, b, lambda x, y: (x * y).cast("double")))
    norm = lambda v: F.sqrt(_fold(F.transform(v, lambda x: (x * x).cast("double"))))
    return 1 - dot / (norm(a) * norm(b))


NAMED = {
    "euclidean": l2,
    "manhattan": l1,
    "hamming": hamming,
    "jaccard": jaccard,
    "jaccard_tokens": jaccard_tokens,
    "doph_estimate": doph_estimate,
    "cosine": cosine,
}


def distance(name: str):
    return NAMED[name]


class Matches:
    """Counts of equal coordinates between rows and fixed centers.

    A center's value is its rank among the centers' values of that coordinate, so that a comparison
    reads two bytes; a row's value that no center has gets the rank beyond the last.
    """

    def __init__(self, c: np.ndarray):
        self.rank_type = np.uint16 if len(c) < 65535 else np.uint32
        self.values, self.ranks = [], []
        for column in c.T:
            found, at = np.unique(column, return_inverse=True)
            self.values.append(found)
            self.ranks.append(at.astype(self.rank_type))
        self.size = len(c)

    def count(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros((len(x), self.size), np.int64)
        few = np.zeros(total.shape, np.uint8)
        same = np.empty(total.shape, bool)
        for j, (found, ranks) in enumerate(zip(self.values, self.ranks, strict=True)):
            at = np.searchsorted(found, x[:, j])
            known = found[np.minimum(at, len(found) - 1)] == x[:, j]
            own = np.where(known, at, len(found)).astype(self.rank_type)
            np.equal(own[:, None], ranks[None], out=same)
            np.add(few, same.view(np.uint8), out=few)
            if j % 255 == 254:
                total += few
                few[:] = 0
        return total + few


def numpy_distances(x: np.ndarray, c: np.ndarray, name: str, matches: Matches | None = None) -> np.ndarray:
    """Rows of ``x`` against rows of ``c`` (or of ``matches`` made of them); the numpy twin of the columns."""
    if name == "euclidean":
        d2 = (x * x).sum(1)[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T
        return np.sqrt(np.maximum(d2, 0))
    if name == "manhattan":
        return np.abs(x[:, None] - c[None]).sum(-1)
    m = (matches or Matches(c)).count(x)
    d = x.shape[1]
    if name == "hamming":
        return (d - m).astype(float)
    if name == "doph_estimate":
        return 1 - m / d
    return 1 - m / (2 * d - m)
