"""The three phases as one plan, for each kind of data."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from bucketseed.functions.doph import doph
from bucketseed.operators import packed
from bucketseed.operators.assign import assign_passes
from bucketseed.operators.centers import centroids, modes, numbered
from bucketseed.operators.metrics import PhaseTimer
from bucketseed.operators.seeding import similar_bucket_seeds
from bucketseed.operators.transform import coordinate_tokens, hetero_tokens, kl_buckets, transform_dense
from bucketseed.staging import SMALL_ROWS, staged


@dataclass
class Run:
    """What a run leaves: buckets, seed groups, centers, the assignment, and seconds by phase."""

    members: DataFrame
    groups: DataFrame
    centers: DataFrame
    assigned: DataFrame
    rows: DataFrame
    seconds: dict[str, float] = field(default_factory=dict)


def _finish(members, rows, vec, center, dist, seeding, passes, timer, exact) -> Run:
    with timer("seed"):
        groups = staged(numbered(staged(similar_bucket_seeds(members, **seeding), "seeds")), "numbered")
    make = (lambda: centroids(groups, rows, vec, exact=exact)) if center == "vec" else (lambda: modes(groups, rows, vec))
    return _assigned(members, groups, make, rows, vec, center, dist, passes, timer, exact)


def _assigned(members, groups, make, rows, vec, center, dist, passes, timer, exact) -> Run:
    with timer("assign"):
        centers = staged(make(), "centers")
        assigned = staged(assign_passes(rows, centers, passes, dist, "gemm", vec, center, exact), "assigned")
    return Run(members, groups, centers, assigned, rows, dict(timer.seconds))


def cluster_dense(rows: DataFrame, m: int, t: int, seed: int = 0, mode: str = "ranked", passes: int = 1, exact: bool = True, vec: str = "vec", **seeding) -> Run:
    """rows(id, vec) by projections cut into t parts, group means, Euclidean distance.

    Tables above ``SMALL_ROWS`` are seeded where they are read (``operators/packed.py``); members and groups
    are then worked out again when they are read.
    """
    timer = PhaseTimer()
    plain = {"K", "L", "delta", "prune", "singletons"} >= seeding.keys() and mode == "ranked" and exact
    if plain and packed.fits(rows, vec) and rows.count() > SMALL_ROWS:
        rows = rows.withColumnRenamed(vec, "vec")
        with timer("transform"):
            cuts = packed.cut(rows, m, t, seed)
        if cuts:
            with timer("seed"):
                groups, centers = packed.seeded(rows, cuts, **seeding)
            return _assigned(packed.members(rows, cuts), groups, lambda: centers, rows, "vec", "vec", "euclidean", passes, timer, exact)
    with timer("transform"):
        members = staged(transform_dense(rows, vec, m, t, seed, mode), "members")
    return _finish(members, rows, vec, "vec", "euclidean", seeding, passes, timer, exact)


def cluster_hetero(rows: DataFrame, numeric: list[str], categorical: list[str], K_t: int = 3, L_t: int = 10, bins: int = 10, seed: int = 0, passes: int = 1, mode: str = "ranked", **seeding) -> Run:
    """Mixed records by (attribute, value) tokens, group modes, 1 - Jaccard."""
    timer = PhaseTimer()
    with timer("transform"):
        tokens = staged(hetero_tokens(rows, numeric, categorical, bins, mode=mode), "tokens")
        members = staged(kl_buckets(tokens, "tokens", K_t, L_t, seed), "members")
    return _finish(members, tokens, "tokens", "modes", "jaccard_tokens", seeding, passes, timer, False)


def cluster_sparse(rows: DataFrame, D: int = 400, K_t: int = 2, L_t: int = 20, seed: int = 0, passes: int = 1, densify: str = "rotation", tokens: str = "tokens", **seeding) -> Run:
    """Sets by D densified coordinates, group modes over coordinates, 1 - Jaccard."""
    timer = PhaseTimer()
    with timer("transform"):
        coords = doph(rows, tokens, D, seed, densify)
        coded = staged(coords.select("id", coordinate_tokens("coords").alias("tokens")), "coords")
        members = staged(kl_buckets(coded, "tokens", K_t, L_t, seed + 1), "members")
    return _finish(members, coded, "tokens", "modes", "jaccard_tokens", seeding, passes, timer, False)
