"""Hash families for the distances that have one, behind one contract.

A family gives ``draw(count, seed)`` parameters, ``hash_columns(col)`` and ``p(r)``: the chance
that two points at distance r collide in one function.
"""

from __future__ import annotations

import math
import random
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

from bucketseed.functions.minhash import minhash
from bucketseed.functions.permutations import draw as draw_perms
from bucketseed.functions.projection import cauchy, dot, gaussian


@dataclass
class LshFamily:
    dims: int = 0
    width: float = 1.0
    params: list = field(default_factory=list)
    distance = "euclidean"

    def draw(self, count: int, seed: int) -> LshFamily:
        raise NotImplementedError

    def hash_columns(self, col: Column | str) -> list[Column]:
        raise NotImplementedError

    def p(self, r: float) -> float:
        raise NotImplementedError


class MinHashFamily(LshFamily):
    distance = "jaccard"

    def draw(self, count, seed):
        self.params = draw_perms(count, seed)
        return self

    def hash_columns(self, col):
        return [minhash(col, self.params, i) for i in range(len(self.params))]

    def p(self, r):
        return 1 - r


class _Projected(LshFamily):
    def _offsets(self, count, seed):
        rng = random.Random(seed)
        return [rng.uniform(0, self.width) for _ in range(count)]

    def hash_columns(self, col):
        return [F.floor((dot(col, d) + F.lit(b)) / F.lit(self.width)) for d, b in self.params]


class EuclideanFamily(_Projected):
    distance = "euclidean"

    def draw(self, count, seed):
        self.params = list(zip(gaussian(count, self.dims, seed).tolist(), self._offsets(count, seed), strict=True))
        return self

    def p(self, r):
        if r == 0:
            return 1.0
        c = self.width / r
        normal = 0.5 * math.erfc(c / math.sqrt(2))
        return 1 - 2 * normal - 2 / (math.sqrt(2 * math.pi) * c) * (1 - math.exp(-c * c / 2))


class ManhattanFamily(_Projected):
    distance = "manhattan"

    def draw(self, count, seed):
        self.params = list(zip(cauchy(count, self.dims, seed).tolist(), self._offsets(count, seed), strict=True))
        return self

    def p(self, r):
        if r == 0:
            return 1.0
        c = self.width / r
        return 2 * math.atan(c) / math.pi - math.log(1 + c * c) / (math.pi * c)


class HammingFamily(LshFamily):
    distance = "hamming"

    def draw(self, count, seed):
        rng = random.Random(seed)
        self.params = [rng.randrange(self.dims) for _ in range(count)]
        return self

    def hash_columns(self, col):
        return [F.get(col, F.lit(i)) for i in self.params]

    def p(self, r):
        return 1 - r / self.dims


class CosineFamily(LshFamily):
    """Random hyperplanes; r is the angle in radians."""

    distance = "cosine"

    def draw(self, count, seed):
        self.params = gaussian(count, self.dims, seed).tolist()
        return self

    def hash_columns(self, col):
        return [(dot(col, d) >= 0).cast("bigint") for d in self.params]

    def p(self, r):
        return 1 - r / math.pi


FAMILIES = {
    "jaccard": MinHashFamily,
    "euclidean": EuclideanFamily,
    "manhattan": ManhattanFamily,
    "hamming": HammingFamily,
    "cosine": CosineFamily,
}


def rho(p1: float, p2: float) -> float:
    return math.log(1 / p1) / math.log(1 / p2)


def suggest_params(n: int, p1: float, p2: float) -> dict:
    """Orders of magnitude: m and K grow with log n, L with n to the power rho."""
    log = math.log(max(n, 2))
    return {
        "rho": rho(p1, p2),
        "m": max(1, math.ceil(log)),
        "K": max(1, math.ceil(log / math.log(1 / p2))),
        "L": max(1, math.ceil(n ** rho(p1, p2))),
    }
