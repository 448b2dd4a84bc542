"""Random permutations as column expressions; the same parameters render as SQL."""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The Mersenne prime 2^31 - 1; affine maps are injective on ids below it and stay below 2^62.
PRIME = 2147483647


@dataclass(frozen=True)
class Permutations:
    """``count`` permutations of ids, drawn once from ``seed``.

    ``affine`` is portable SQL for ids below PRIME; ``xx`` is a seeded 64-bit hash for any id.
    """

    params: tuple
    kind: str = "affine"

    def __len__(self) -> int:
        return len(self.params)

    def of(self, value: Column, i: int) -> Column:
        p = self.params[i]
        if self.kind == "xx":
            return F.xxhash64(F.lit(p), value)
        return (value * F.lit(p[0]) + F.lit(p[1])) % F.lit(PRIME)

    def sql(self, value: str, i: int) -> str:
        if self.kind != "affine":
            raise ValueError("only affine permutations render as SQL")
        a, b = self.params[i]
        return f"(({value} * {a} + {b}) % {PRIME})"


def affine_perms(count: int, seed: int) -> Permutations:
    rng = random.Random(seed)
    return Permutations(tuple((rng.randrange(1, PRIME), rng.randrange(PRIME)) for _ in range(count)))


def xx_perms(count: int, seed: int) -> Permutations:
    rng = random.Random(seed)
    return Permutations(tuple(rng.getrandbits(62) for _ in range(count)), "xx")


def draw(count: int, seed: int, kind: str = "affine") -> Permutations:
    return affine_perms(count, seed) if kind == "affine" else xx_perms(count, seed)
