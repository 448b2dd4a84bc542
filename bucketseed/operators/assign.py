"""Phase 3, second half: every row goes once to its nearest center; ties go to the least seed."""

from __future__ import annotations

import uuid
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.functions.distances import Matches, distance, numpy_distances
from bucketseed.functions.minhash import minhash_values
from bucketseed.functions.permutations import draw
from bucketseed.operators.centers import centroids, modes
from bucketseed.operators.postings import SetIndex, expand, made, narrow
from bucketseed.operators.ranking import ranked
from bucketseed.staging import staged

#: Centers are broadcast whole up to this size; beyond it they come in blocks of it.
CENTER_BYTES = 200_000_000
#: Centers that are looked up come in blocks of this size: a worker's index takes four times as much.
INDEX_BYTES = 100_000_000
#: Rows whose distances to a block of centers stay in a processor's cache.
SLICE = 1024
#: Values of coordinates that are looked up are below.
KEYED = 1 << 48
#: Coordinates of pairs that are compared at once.
PAIR_CELLS = 16_000_000


def assign_sql(data: DataFrame, centers: DataFrame, dist: str = "euclidean", vec: str = "vec", center: str = "vec") -> DataFrame:
    """Broadcast nested loop in columns; exact on fixed-point vectors. For few centers.

    Centers beyond ``CENTER_BYTES`` (see ``assign``) come here in chunks below it.
    """
    c = F.broadcast(centers.select("seed_id", F.col(center).alias("_c")))
    d = distance(dist)(F.col(vec), F.col("_c"))
    near = data.select("id", vec).crossJoin(c).groupBy("id").agg(F.min(F.struct(d.alias("dist"), "seed_id")).alias("b"))
    return near.select("id", F.col("b.seed_id").alias("cluster_id"), F.col("b.dist").alias("dist"))


def collected(centers: DataFrame, center: str) -> tuple[np.ndarray, np.ndarray]:
    rows = centers.select("seed_id", center).orderBy("seed_id").toArrow()
    ids = rows["seed_id"].to_numpy()
    flat = rows[center].combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return ids, flat.reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))


def assign_blocks(data: DataFrame, ids: np.ndarray, vectors: np.ndarray, dist: str = "euclidean", vec: str = "vec", block: int = 4096) -> DataFrame:
    """Arrow batches against blocks of centers; distances by matrix product where there is one, equal coordinates by ``Lookup``."""
    if vectors.nbytes > CENTER_BYTES:
        return _assign_chunks(data, ids, vectors, dist, vec, block)
    if dist == "jaccard_tokens" and len(ids) and np.abs(vectors).max() < KEYED:
        rows = data.select("id", F.col(vec).alias("tokens"), F.lit(None).cast("bigint").alias("was"), F.lit(0).alias("m"))
        return reassign(rows, ids, vectors, np.ones(len(ids), bool)).select("id", "cluster_id", "dist")
    held = data.sparkSession.sparkContext.broadcast((ids, vectors))

    def run(batches):
        names, c = held.value
        c = c.astype(float) if dist in ("euclidean", "manhattan") else c
        step = max(1, min(block, 4_000_000 // max(c.size // max(len(c), 1), 1) // 64)) if dist == "manhattan" else block
        made = [None if dist in ("euclidean", "manhattan") else Matches(c[at : at + step]) for at in range(0, len(c), step)]
        for batch in batches:
            n = batch.num_rows
            flat = batch.column("vec").flatten().to_numpy(zero_copy_only=False)
            x = flat.reshape(n, -1)
            x = x.astype(float) if dist in ("euclidean", "manhattan") else x
            best, who = np.full(n, np.inf), np.zeros(n, np.int64)
            rows = SLICE if dist == "euclidean" else 64
            for r in range(0, n, rows):
                for at in range(0, len(c), step):
                    d = numpy_distances(x[r : r + rows], c[at : at + step], dist, made[at // step])
                    i = d.argmin(1)
                    v = d[np.arange(len(d)), i]
                    closer = v < best[r : r + rows]
                    best[r : r + rows] = np.where(closer, v, best[r : r + rows])
                    who[r : r + rows] = np.where(closer, at + i, who[r : r + rows])
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.array(names[who] if len(names) else who), pa.array(best)], ["id", "cluster_id", "dist"]
            )

    rows = data.select("id", F.col(vec).alias("vec"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, cluster_id bigint, dist double")


def _assign_chunks(data, ids, vectors, dist, vec, block):
    """Centers above the broadcast bound: one pass over the rows for each chunk, then the minimum."""
    per = max(1, CENTER_BYTES // max(vectors[0].nbytes, 1))
    out = None
    for at in range(0, len(ids), per):
        part = assign_blocks(data, ids[at : at + per], vectors[at : at + per], dist, vec, block)
        out = part if out is None else out.unionByName(part)
    near = out.groupBy("id").agg(F.min(F.struct("dist", "cluster_id")).alias("b"))
    return near.select("id", "b.cluster_id", "b.dist")


def assign_match(data: DataFrame, centers: DataFrame, tokens: str = "tokens", center: str = "modes") -> DataFrame:
    """Rows of d coordinates by equal coordinates, over an inverted index of the centers that each worker makes.

    Centers beyond ``CENTER_BYTES`` (see ``assign``) come here in chunks below it.
    """
    ids, vectors = collected(centers, center)
    rows = data.select("id", F.col(tokens).alias("tokens"))
    if not len(ids):
        return rows.select("id", F.lit(None).cast("bigint").alias("cluster_id"), F.lit(1.0).alias("dist"))
    d = vectors.shape[1]
    held = data.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, ids, narrow(vectors)))
    keyed = lambda x: (x.astype(np.int64) * d + np.arange(d)).ravel()

    def run(batches):
        name, ids, c = held.value
        k = len(ids)
        index = made(name, lambda flat, offs: SetIndex(keyed(flat.reshape(k, d)), offs), c.ravel(), np.arange(k + 1) * d)
        for batch in batches:
            n = batch.num_rows
            x = batch.column("tokens").flatten().to_numpy(zero_copy_only=False).reshape(n, d)
            m, who = np.zeros(n, np.int64), np.zeros(n, np.int64)
            for r, q, shared in index.shared(keyed(x), np.arange(n + 1) * d):
                if len(r):
                    # most equal coordinates, then the least seed
                    first = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
                    best = np.maximum.reduceat(shared.astype(np.int64) * k + (k - 1 - q), first)
                    m[r[first]], who[r[first]] = best // k, k - 1 - best % k
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(ids[who]), pa.array(1 - m / (2 * d - m))], ["id", "cluster_id", "dist"])

    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, cluster_id bigint, dist double")


class Lookup:
    """Rows of d coordinates against centers, by an inverted index or, where that has more to count, side by side."""

    def __init__(self, c: np.ndarray):
        self.c, self.d = c, c.shape[1]
        self._index: SetIndex | None = None
        self._dense: list[Matches] = []

    def _keyed(self, x: np.ndarray) -> np.ndarray:
        return (np.clip(x, -KEYED, KEYED).astype(np.int64) * self.d + np.arange(self.d)).ravel()

    def best(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each row's most equal coordinates and the first center that has them.

        A hit of the index costs about 100 comparisons, or 20 where a row has many; a few rows and centers tell which way is shorter.
        """
        n, k = len(x), len(self.c)
        m, who = np.zeros(n, np.int64), np.zeros(n, np.int64)
        share = (x[:: n // 64 + 1, None] == self.c[None, :: k // 64 + 1]).mean()
        if share < 0.01 or (share < 0.05 and k >= 2_000):
            centers = np.arange(k + 1) * self.d
            self._index = self._index or SetIndex(self._keyed(self.c), centers)
            if share * self.d * k > 1_000:
                return self._counted(x)
            for r, q, shared in self._index.shared(self._keyed(x), np.arange(n + 1) * self.d):
                if len(r):
                    first = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
                    most = np.maximum.reduceat(shared.astype(np.int64) * k + (k - 1 - q), first)
                    m[r[first]], who[r[first]] = most // k, k - 1 - most % k
            return m, who
        step = 4096
        self._dense = self._dense or [Matches(self.c[at : at + step]) for at in range(0, k, step)]
        for r in range(0, n, 64):
            part = slice(r, min(r + 64, n))
            for j, block in enumerate(self._dense):
                same = block.count(x[part])
                i = same.argmax(1)
                v = same[np.arange(len(i)), i]
                more = v > m[part]
                m[part], who[part] = np.where(more, v, m[part]), np.where(more, j * step + i, who[part])
        return m, who

    def _counted(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """``best`` by counts over all centers, a row at a time: many hits need no sort."""
        n, k, posted = len(x), len(self.c), self._index.who
        m, who = np.zeros(n, np.int64), np.zeros(n, np.int64)
        starts, lengths = self._index.spans(self._keyed(x))
        spans = [[slice(a, a + b) for a, b in zip(*part, strict=True)] for part in zip(starts.reshape(n, -1).tolist(), lengths.reshape(n, -1).tolist(), strict=True)]
        for r, own in enumerate(spans):
            count = np.bincount(np.concatenate([posted[part] for part in own]), minlength=k)
            who[r] = count.argmax()
            m[r] = count[who[r]]
        return m, who


def reassign(rows: DataFrame, ids: np.ndarray, c: np.ndarray, changed: np.ndarray) -> DataFrame:
    """(id, cluster_id, dist, was, m, work) of ``rows`` (id, tokens, was, m): their last center, or null, and its equal coordinates.

    ``changed`` marks the centers that moved since. The others were no nearer than the last one, so a
    row whose last center is as near as before is compared with the changed ones alone.
    """
    d = c.shape[1]
    held = rows.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, ids, narrow(c), changed))

    def run(batches):
        name, ids, c, changed = held.value
        k, moved = len(ids), np.flatnonzero(changed)

        def make(flat, offs):
            flat = flat.reshape(k, d)
            return Lookup(flat), Lookup(flat[moved]) if 2 * len(moved) < k else None

        whole, some = made(name, make, c.ravel(), np.arange(k + 1) * d)
        for batch in batches:
            n = batch.num_rows
            x = batch.column("tokens").flatten().to_numpy(zero_copy_only=False).reshape(n, d)
            was = batch.column("was").fill_null(-1).to_numpy(zero_copy_only=False)
            first = batch.column("was").is_null().to_numpy(zero_copy_only=False)
            before = batch.column("m").to_numpy(zero_copy_only=False)
            who = np.minimum(np.searchsorted(ids, was), k - 1)
            m = np.where(first | (ids[who] != was), -1, (x == c[who]).sum(1))
            scan = m < np.maximum(before, 0)
            work = np.where(scan, k, len(moved) + 1)
            if scan.any():
                m[scan], who[scan] = whole.best(x[scan])
            rest = np.flatnonzero(~scan)
            if len(rest) and len(moved):
                v, at = (some or whole).best(x[rest])
                at = moved[at] if some else at
                nearer = (v > m[rest]) | ((v == m[rest]) & (at < who[rest]))
                m[rest[nearer]], who[rest[nearer]] = v[nearer], at[nearer]
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.array(ids[who]), pa.array(1 - m / (2 * d - m)), batch.column("was"), pa.array(m.astype(np.int32)), pa.array(work.astype(np.int64))],
                ["id", "cluster_id", "dist", "was", "m", "work"],
            )

    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, cluster_id bigint, dist double, was bigint, m int, work bigint")


def assign_shortlist(data: DataFrame, centers: DataFrame, tokens: str = "tokens", center: str = "modes", K: int = 2, L: int = 10, seed: int = 5) -> DataFrame:
    """Only centers that share a signature are compared; rows without any get the full scan.

    Centers are broadcast with their hash values, in chunks below ``CENTER_BYTES``, and rows are judged where they
    are read: neither signatures nor candidates are exchanged.
    """
    perms = draw(K * L, seed)
    hashed = lambda df, who, c: df.select(who, F.col(c).alias("tokens"), minhash_values(c, perms).alias("h"))
    rows, held = hashed(data, "id", tokens), hashed(centers, "seed_id", center)
    size = centers.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size(center)), F.lit(1)).alias("dims")).first()
    per = max(1, CENTER_BYTES // (8 * (size["dims"] + K * L)))
    if size["n"] <= per:
        return _shortlisted(rows, held.toArrow(), K, L).select("id", "cluster_id", "dist")
    placed = ranked(held, ["seed_id"], ["seed_id", "tokens", "h"])
    parts = [
        staged(_shortlisted(rows, placed.filter(F.col("rank").between(at, at + per - 1)).select("seed_id", "tokens", "h").toArrow(), K, L), "chunk")
        for at in range(0, size["n"], per)
    ]
    # a chunk without candidates has its nearest of all, which counts where no chunk has any
    near = reduce(DataFrame.unionByName, parts).groupBy("id").agg(F.min(F.struct("scanned", "dist", "cluster_id")).alias("b"))
    return near.select("id", "b.cluster_id", "b.dist")


def _shortlisted(rows: DataFrame, centers: pa.Table, K: int, L: int) -> DataFrame:
    """(id, cluster_id, dist, scanned) of ``rows`` (id, tokens, h); ``scanned`` where no center shares a signature."""
    schema = f"id {dict(rows.dtypes)['id']}, cluster_id bigint, dist double, scanned boolean"
    if not centers.num_rows:
        return rows.select("id", F.lit(None).cast("bigint").alias("cluster_id"), F.lit(1.0).alias("dist"), F.lit(True).alias("scanned"))
    centers = centers.sort_by("seed_id").combine_chunks()
    k = centers.num_rows
    wide = lambda column, n: column.flatten().fill_null(-1).to_numpy(zero_copy_only=False).reshape(n, -1)
    held = rows.sparkSession.sparkContext.broadcast(
        (uuid.uuid4().hex, centers["seed_id"].to_numpy(), narrow(wide(centers["tokens"].combine_chunks(), k)), narrow(wide(centers["h"].combine_chunks(), k)))
    )

    def run(batches):
        name, ids, c, h = held.value
        k, d = c.shape

        def make(flat, offs):
            tables = [np.unique(h[:, at : at + K], axis=0, return_inverse=True) for at in range(0, K * L, K)]
            return Lookup(flat.reshape(k, d)), [(_keys(found), np.argsort(of.ravel(), kind="stable"), np.searchsorted(np.sort(of.ravel()), np.arange(len(found) + 1))) for found, of in tables]

        whole, tables = made(name, make, c.ravel(), np.arange(k + 1) * d)
        for batch in batches:
            n = batch.num_rows
            x, own = wide(batch.column("tokens"), n), wide(batch.column("h"), n)
            m, who = np.full(n, -1), np.zeros(n, np.int64)
            for l, (found, order, starts) in enumerate(tables):
                at = [found.get(key, -1) for key in map(tuple, own[:, l * K : l * K + K].tolist())]
                at = np.array(at, np.int64)
                some = np.flatnonzero(at >= 0)
                sizes = starts[at[some] + 1] - starts[at[some]]
                ends = np.cumsum(sizes)
                first = 0
                while first < len(some):
                    # pairs of a slice hold about PAIR_CELLS coordinates
                    done = ends[first - 1] if first else 0
                    last = max(first + 1, int(np.searchsorted(ends, done + PAIR_CELLS // d, "right")))
                    mine, many = some[first:last], sizes[first:last]
                    q = order[expand(starts[at[mine]], many)]
                    r = np.repeat(mine, many)
                    same = np.concatenate([(x[r[i : i + 4096]] == c[q[i : i + 4096]]).sum(1) for i in range(0, len(r), 4096)])
                    edges = np.cumsum(many) - many
                    most = np.maximum.reduceat(same.astype(np.int64) * k + (k - 1 - q), edges)
                    v, w = most // k, k - 1 - most % k
                    nearer = (v > m[mine]) | ((v == m[mine]) & (w < who[mine]))
                    m[mine[nearer]], who[mine[nearer]] = v[nearer], w[nearer]
                    first = last
            scanned = m < 0
            if scanned.any():
                m[scanned], who[scanned] = whole.best(x[scanned])
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.array(ids[who]), pa.array(1 - m / (2 * d - m)), pa.array(scanned)], ["id", "cluster_id", "dist", "scanned"]
            )

    return rows.mapInArrow(run, schema)


def _keys(values: np.ndarray) -> dict[tuple, int]:
    return {tuple(v): i for i, v in enumerate(values.tolist())}


def assign(data: DataFrame, centers: DataFrame, dist: str = "euclidean", strategy: str = "gemm", vec: str = "vec", center: str = "vec") -> DataFrame:
    """(id, cluster_id, dist) by one of: sql, gemm, match, shortlist."""
    if strategy in ("sql", "gemm", "match"):
        one = {
            "sql": lambda c: assign_sql(data, c, dist, vec, center),
            "gemm": lambda c: assign_blocks(data, *collected(c, center), dist, vec),
            "match": lambda c: assign_match(data, c, vec, center),
        }[strategy]
        size = centers.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size(center)), F.lit(1)).alias("dims")).first()
        per = max(1, (min(CENTER_BYTES, INDEX_BYTES) if dist == "jaccard_tokens" else CENTER_BYTES) // (8 * size["dims"]))
        if size["n"] <= per:
            return one(centers)
        placed = ranked(centers, ["seed_id"], ["seed_id", center])
        parts = [
            staged(one(placed.filter(F.col("rank").between(at, at + per - 1)).select("seed_id", center)), "chunk")
            for at in range(0, size["n"], per)
        ]
        near = reduce(DataFrame.unionByName, parts).groupBy("id").agg(F.min(F.struct("dist", "cluster_id")).alias("b"))
        return near.select("id", "b.cluster_id", "b.dist")
    if strategy == "shortlist":
        return assign_shortlist(data, centers, vec, center)
    raise ValueError(strategy)


def members_of(assigned: DataFrame) -> DataFrame:
    return assigned.select(F.col("cluster_id").alias("seed_id"), "id")


def assign_passes(data: DataFrame, centers: DataFrame, passes: int = 1, dist: str = "euclidean", strategy: str = "gemm", vec: str = "vec", center: str = "vec", exact: bool = True) -> DataFrame:
    """Assign; for each further pass move centers to their members' mean or mode and assign again."""
    out = assign(data, centers, dist, strategy, vec, center)
    for _ in range(passes - 1):
        out = staged(out, "pass")
        moved = centroids(members_of(out), data, vec, exact=exact) if center == "vec" else modes(members_of(out), data, vec)
        out = assign(data, staged(moved, "centers"), dist, strategy, vec, center)
    return out


def k_star(assigned: DataFrame) -> DataFrame:
    return assigned.agg(F.count_distinct("cluster_id").alias("k_star"))
