"""Column expressions that the native corpus operators share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed: separators of plain words, and of alphanumeric words (after A-Z were lower-cased).
SPACE = r"[\x20\x09-\x0D]+"
NOT_ALNUM = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same words in a text whose A-Z are still there: for counting alone.
NOT_ALNUM_CASED = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def ascii_lower(text: Column) -> Column:
    """A-Z only; other letters keep their case, unlike ``lower``."""
    return F.translate(text, UPPER, UPPER.lower())


def pieces(text: Column, separators: str) -> Column:
    """Non-empty pieces of ``text`` between runs of separators; null gives none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), separators), lambda w: w != "")


def gram_hashes(hashes: Column, length: int) -> Column:
    """A 64-bit hash for each run of ``length`` neighbours; none if there are fewer."""
    last = F.size(hashes) - length
    return F.when(
        last >= 0,
        F.transform(
            F.sequence(F.lit(0), last),
            lambda i: F.xxhash64(*[F.get(hashes, i + k) for k in range(length)]),
        ),
    ).otherwise(F.array().cast("array<bigint>"))
