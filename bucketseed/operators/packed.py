"""Dense seeding without an exchange of rows: a row's buckets, votes and groups are worked out where it is read.

Tables are cut at exact ranks that a few counting passes find, so no projection is sorted. Buckets, bins and
groups are few (m * t at most) and known to every task; a row's own parts then tell which bins and groups it is in.
Results are those of ``transform_dense``, ``similar_bucket_seeds`` and ``centroids`` for rows with distinct ids.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.functions.permutations import PRIME, Permutations, draw
from bucketseed.functions.projection import integer_directions
from bucketseed.operators.seeding import make_bins
from bucketseed.operators.transform import bucket_key

#: First bins of a table's projections, and bins that a span is then split into.
BINS, SPLIT = 4096, 64
#: Rows around cuts that the driver orders.
COLLECTED = 500_000
#: Rows that are worked on at once, and flags of rows and bins.
SLICE, FLAGS = 100_000, 50_000_000
INTEGERS = ("tinyint", "smallint", "int", "bigint")


def fits(rows: DataFrame, vec: str) -> bool:
    """Whether ids and vectors are integers."""
    kinds = dict(rows.dtypes)
    return kinds["id"] in INTEGERS and kinds[vec] in [f"array<{kind}>" for kind in INTEGERS]


def _columns(batch) -> tuple[np.ndarray, np.ndarray]:
    n = batch.num_rows
    return batch.column("id").to_numpy().astype(np.int64), batch.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(np.int64)


def _sliced(batches, rows: int = SLICE):
    """(ids, vectors) of up to ``rows`` rows each."""
    held, n = [], 0
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            part = batch.slice(at, rows)
            if n + part.num_rows > rows:
                yield tuple(np.concatenate(c) for c in zip(*held, strict=True))
                held, n = [], 0
            held.append(_columns(part))
            n += part.num_rows
    if held:
        yield tuple(np.concatenate(c) for c in zip(*held, strict=True))


@dataclass
class Cuts:
    """For each table the (h, id) that its parts but the first begin with."""

    directions: np.ndarray  # tables by dims
    h: list[np.ndarray]
    ids: list[np.ndarray]
    t: int

    def parts(self, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Tables by rows."""
        out = np.empty((len(self.h), len(ids)), np.int32)
        for j, (h, first) in enumerate(zip(self.h, self.ids, strict=True)):
            own = x @ self.directions[j]
            part = np.searchsorted(h, own, "right")
            if len(h):
                # of cuts within equal values, those at greater ids are not reached
                tied = np.flatnonzero((part > 0) & (h[part - 1] == own))
                for top in np.unique(part[tied]):
                    same = tied[part[tied] == top]
                    low = np.searchsorted(h, h[top - 1], "left")
                    part[same] = low + np.searchsorted(first[low:top], ids[same], "right")
            out[j] = part
        return out


def _shape(rows: DataFrame, m: int, seed: int):
    """(rows, directions, least and most projections), or None where columns have to do: nulls, ragged rows, large numbers."""
    first = rows.select("vec").first()
    if first is None or not first[0]:
        return None
    dims = len(first[0])
    directions = np.array(integer_directions(m, dims, seed), np.int64)
    top = (1 << 61) // max(1, int(np.abs(directions).sum(1).max()))

    def run(batches):
        n, odd, low, high = 0, 0, np.full(m, 1 << 62), np.full(m, -(1 << 62))
        for batch in batches:
            if not batch.num_rows:
                continue
            n += batch.num_rows
            vec = batch.column("vec")
            sizes = vec.value_lengths()
            if batch.column("id").null_count or vec.null_count or vec.flatten().null_count or not (sizes.to_numpy(zero_copy_only=False) == dims).all():
                odd += 1
                continue
            ids, x = _columns(batch)
            if ids.min() < 0 or ids.max() >= PRIME or x.min() < -top or x.max() > top:
                odd += 1
                continue
            h = x @ directions.T
            low, high = np.minimum(low, h.min(0)), np.maximum(high, h.max(0))
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([odd]), pa.array([low.tolist()]), pa.array([high.tolist()])], ["n", "odd", "low", "high"])

    got = rows.mapInArrow(run, "n bigint, odd bigint, low array<bigint>, high array<bigint>").collect()
    n = sum(r["n"] for r in got)
    if not n or any(r["odd"] for r in got):
        return None
    return n, directions, np.min([r["low"] for r in got], 0), np.max([r["high"] for r in got], 0)


class _Spans:
    """Disjoint intervals of keys of one group, each with the ranks that are sought in it."""

    def __init__(self, low: int, high: int, ranks: list[int], total: int):
        self.lows, self.highs, self.below, self.counts, self.ranks = [low], [high], [0], [total], [ranks]

    def bins(self) -> np.ndarray:
        """Least keys of all bins of all spans in order, and the spans they belong to."""
        n = BINS if len(self.lows) == 1 else SPLIT
        edges = [low + (high - low + 1) * i // n for low, high in zip(self.lows, self.highs, strict=True) for i in range(n) if i == 0 or (high - low + 1) * i // n > (high - low + 1) * (i - 1) // n]
        return np.array(edges, np.int64)

    def narrowed(self, edges: np.ndarray, counts: np.ndarray) -> None:
        """To the bins that hold ranks."""
        old = list(zip(self.lows, self.highs, self.below, self.ranks, strict=True))
        self.lows, self.highs, self.below, self.counts, self.ranks = [], [], [], [], []
        for low, high, below, ranks in old:
            at, end = np.searchsorted(edges, [low, high], "left")[0], np.searchsorted(edges, high, "right")
            before = below + np.concatenate([[0], np.cumsum(counts[at:end])])
            tops = np.append(edges[at + 1 : end] - 1, high)
            of = np.searchsorted(before, ranks, "right") - 1
            for i in np.unique(of):
                self.lows.append(int(edges[at + i]))
                self.highs.append(int(tops[i]))
                self.below.append(int(before[i]))
                self.counts.append(int(counts[at + i]))
                self.ranks.append([r for r, o in zip(ranks, of, strict=True) if o == i])


def _inside(keys: np.ndarray, lows: np.ndarray, highs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the keys that are in a span, and their spans."""
    at = np.searchsorted(lows, keys, "right") - 1
    rows = np.flatnonzero((at >= 0) & (keys <= highs[np.maximum(at, 0)]))
    return rows, at[rows]


def _narrow(rows: DataFrame, keyed, spans: list[_Spans]) -> None:
    """Counts keys until the spans hold few rows or single keys. ``keyed`` gives each group's keys of a slice."""
    while True:
        wide = sum(c for s in spans for c, low, high in zip(s.counts, s.lows, s.highs, strict=True) if high > low)
        if wide <= COLLECTED:
            return
        edges = [s.bins() for s in spans]
        bounds = [(np.array(s.lows), np.array(s.highs)) for s in spans]
        starts = np.concatenate([[0], np.cumsum([len(e) for e in edges])])

        def run(batches, edges=edges, bounds=bounds, starts=starts):
            total = np.zeros(starts[-1], np.int64)
            for ids, x in _sliced(batches):
                for j, keys in enumerate(keyed(ids, x)):
                    own, _ = _inside(keys, *bounds[j])
                    at = np.searchsorted(edges[j], keys[own], "right") - 1
                    total[starts[j] : starts[j + 1]] += np.bincount(at, minlength=len(edges[j]))
            there = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(total[there])], ["slot", "n"])

        got = rows.mapInArrow(run, "slot bigint, n bigint").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
        counts = np.zeros(starts[-1], np.int64)
        counts[got["slot"].to_numpy()] = got["n"].to_numpy()
        for j, s in enumerate(spans):
            s.narrowed(edges[j], counts[starts[j] : starts[j + 1]])


def cut(rows: DataFrame, m: int, t: int, seed: int = 0) -> Cuts | None:
    """The cuts of ``rows`` (id, vec) along m projections into t parts of equal count, ties by id."""
    shape = _shape(rows, m, seed)
    if shape is None:
        return None
    n, directions, low, high = shape
    small, large = divmod(n, t)
    ranks = [p * small + min(p, large) for p in range(1, t)]
    ranks = [r for r in ranks if r < n]
    if not ranks:
        return Cuts(directions, [np.zeros(0, np.int64)] * m, [np.zeros(0, np.int64)] * m, t)
    spans = [_Spans(int(a), int(b), ranks, n) for a, b in zip(low, high, strict=True)]
    project = lambda ids, x: (x @ d for d in directions)
    _narrow(rows, project, spans)
    # values that very many rows share are told apart by their ids
    tied = [(j, i) for j, s in enumerate(spans) for i in range(len(s.lows)) if s.lows[i] == s.highs[i] and s.counts[i] > COLLECTED // (m * t) + 1]
    values = [(j, spans[j].lows[i]) for j, i in tied]
    within = [_Spans(0, PRIME, [r - spans[j].below[i] for r in spans[j].ranks[i]], spans[j].counts[i]) for j, i in tied]
    of_ties = lambda ids, x: (ids[x @ directions[j] == v] for j, v in values)
    if within:
        _narrow(rows, of_ties, within)
    free = [[i for i in range(len(s.lows)) if (j, i) not in set(tied)] for j, s in enumerate(spans)]
    bounds = [(np.array([s.lows[i] for i in f], np.int64), np.array([s.highs[i] for i in f], np.int64)) for s, f in zip(spans, free, strict=True)]
    inner = [(np.array(s.lows), np.array(s.highs)) for s in within]

    def run(batches):
        found = []
        for ids, x in _sliced(batches):
            for j, h in enumerate(project(ids, x)):
                if len(bounds[j][0]):
                    own, at = _inside(h, *bounds[j])
                    found.append((np.full(len(own), j), at, h[own], ids[own]))
            for j, keys in enumerate(of_ties(ids, x)):
                own, at = _inside(keys, *inner[j])
                found.append((np.full(len(own), m + j), at, np.zeros(len(own), np.int64), keys[own]))
        cells = [np.concatenate(c) for c in zip(*found, strict=True)] if found else [np.zeros(0, np.int64)] * 4
        yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in cells], ["g", "span", "h", "id"])

    got = rows.mapInArrow(run, "g bigint, span bigint, h bigint, id bigint").toArrow()
    g, span, h, ids = (got[c].to_numpy() for c in ("g", "span", "h", "id"))
    order = np.lexsort((ids, h, span, g))
    g, span, h, ids = g[order], span[order], h[order], ids[order]
    cuts: list[list[tuple[int, int, int]]] = [[] for _ in range(m)]
    for j, f in enumerate(free):
        for at, i in enumerate(f):
            first = np.searchsorted(g, j) + np.searchsorted(span[g == j], at)
            cuts[j] += [(r, int(h[first + r - spans[j].below[i]]), int(ids[first + r - spans[j].below[i]])) for r in spans[j].ranks[i]]
    for j, s in enumerate(within):
        table, value = values[j]
        below = spans[table].below[tied[j][1]]
        for at in range(len(s.lows)):
            first = np.searchsorted(g, m + j) + np.searchsorted(span[g == m + j], at)
            cuts[table] += [(below + r, value, int(ids[first + r - s.below[at]])) for r in s.ranks[at]]
    cuts = [sorted(c) for c in cuts]
    return Cuts(directions, [np.array([c[1] for c in own], np.int64) for own in cuts], [np.array([c[2] for c in own], np.int64) for own in cuts], t)


def members(rows: DataFrame, cuts: Cuts) -> DataFrame:
    """(bucket_id, table_id, id), as ``transform_dense`` gives them."""
    held = rows.sparkSession.sparkContext.broadcast(cuts)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                parts = held.value.parts(*_columns(batch)).T
                offsets = pa.array(np.arange(len(parts) + 1, dtype=np.int32) * parts.shape[1])
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.ListArray.from_arrays(offsets, pa.array(parts.ravel()))], ["id", "parts"])

    packed = rows.select("id", "vec").mapInArrow(run, f"id {dict(rows.dtypes)['id']}, parts array<int>")
    return packed.select("id", F.posexplode("parts").alias("table_id", "part")).select(bucket_key(F.col("table_id"), F.col("part")).alias("bucket_id"), "table_id", "id")


def _permuted(ids: np.ndarray, perm: tuple[int, int]) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(perm[0]) + np.uint64(perm[1])) % np.uint64(PRIME)).astype(np.int64)


def _least(schema_rows: DataFrame, hashes: int) -> DataFrame:
    """Sizes and minima of (set, size, h) over tasks."""
    return schema_rows.groupBy("set").agg(F.sum("size").alias("size"), *[F.min(F.get("h", F.lit(i))).alias(f"h{i}") for i in range(hashes)])


def _signatures(rows: DataFrame, cuts: Cuts, perms: Permutations) -> DataFrame:
    """(bucket_id, size, h0, ...): ``bucket_signatures`` of the buckets."""
    held = rows.sparkSession.sparkContext.broadcast(cuts)
    m, t, count = len(cuts.h), cuts.t, len(perms)

    def run(batches):
        sizes, least = np.zeros(m * t, np.int64), np.full((count, m * t), 1 << 62)
        for ids, x in _sliced(batches):
            buckets = held.value.parts(ids, x) + np.arange(m, dtype=np.int32)[:, None] * t
            sizes += np.bincount(buckets.ravel(), minlength=m * t)
            seen = sizes > 0
            for i, perm in enumerate(perms.params):
                h = _permuted(ids, perm)
                at = 0
                while at < len(h):
                    # a row above every bucket's minimum changes none
                    most = least[i][seen].max()
                    to = min(len(h), at + (1000 if most >= PRIME else len(h)))
                    some = at + np.flatnonzero(h[at:to] < most)
                    np.minimum.at(least[i], buckets[:, some].ravel(), np.broadcast_to(h[some], (m, len(some))).ravel())
                    at = to
        there = np.flatnonzero(sizes)
        yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(sizes[there]), pa.array(least[:, there].T.tolist(), pa.list_(pa.int64()))], ["set", "size", "h"])

    got = _least(rows.mapInArrow(run, "set bigint, size bigint, h array<bigint>"), count)
    name = bucket_key(F.floor(F.col("set") / t), F.col("set") % t)
    return got.select(name.alias("bucket_id"), *[c for c in got.columns if c != "set"])


@dataclass
class Votes:
    """Sets of buckets (bins), and sets of these (bins of groups), each once, with what they are called."""

    cuts: Cuts
    bins: list[np.ndarray]  # bucket numbers
    seconds: list[tuple[np.ndarray, np.ndarray]] | None = None  # places in bins, and how often each counts

    def slices(self, batches):
        """Rows in slices whose flags take little memory."""
        return _sliced(batches, max(1_000, min(SLICE, FLAGS // max(1, len(self.bins)))))

    def groups(self, ids: np.ndarray, x: np.ndarray):
        """Yields for each bin which rows are in more than half of its buckets."""
        parts, t = self.cuts.parts(ids, x), self.cuts.t
        parts = parts.astype(np.uint8) if t <= 256 else parts
        for own in self.bins:
            if len(np.unique(own // t)) * 2 <= len(own):  # a row is in one bucket of a table
                yield np.zeros(len(ids), bool)
                continue
            votes = np.zeros(len(ids), np.uint8 if len(own) < 128 else np.int32)
            for bucket in own.tolist():
                votes += parts[bucket // t] == bucket % t
            yield votes > len(own) // 2

    def finals(self, ids: np.ndarray, x: np.ndarray):
        """Yields for each bin of groups its rows' votes, 0 where they are no more than half."""
        inside = list(self.groups(ids, x))
        for own, weights in self.seconds:
            votes = sum(inside[i].astype(np.int32) * np.int32(w) for i, w in zip(own, weights, strict=True))
            yield np.where(votes * 2 > weights.sum(), votes, 0)


def _together(rows: list, number) -> tuple[dict[str, int], list]:
    """Bins by name, each set of members once: ``rows`` are (bin_id, bucket_id)."""
    held: dict[str, list] = {}
    for r in rows:
        held.setdefault(r["bin_id"], []).append(number(r["bucket_id"]))
    places: dict[tuple, int] = {}
    names = {name: places.setdefault(tuple(sorted(own)), len(places)) for name, own in held.items()}
    return names, list(places)


def seeded(rows: DataFrame, cuts: Cuts, K: int = 3, L: int = 20, delta: int = 10, seed: int = 0, prune: bool = True, singletons: str = "keep") -> tuple[DataFrame, DataFrame]:
    """(groups, centers): what ``similar_bucket_seeds`` finds, numbered, and the groups' ``centroids``.

    Two passes: the first gives the groups' sizes and signatures, the second counts and sums the groups that are kept.
    """
    spark, t = rows.sparkSession, cuts.t
    first, second = draw(K * L, seed), draw(K, seed + 1)
    number = lambda name: int(name.split(":")[0]) * t + int(name.split(":")[1])
    named, bins = _together(make_bins(_signatures(rows, cuts, first), K, L, 2, delta, prune).select("bin_id", "bucket_id").collect(), number)
    votes = Votes(cuts, [np.array(b) for b in bins])
    held = spark.sparkContext.broadcast(votes)

    def sign(batches):
        votes = held.value
        sizes, least = np.zeros(len(votes.bins), np.int64), np.full((len(votes.bins), K), 1 << 62)
        for ids, x in votes.slices(batches):
            h = [_permuted(ids, p) for p in second.params]
            for i, inside in enumerate(votes.groups(ids, x)):
                own = np.flatnonzero(inside)
                if len(own):
                    sizes[i] += len(own)
                    for k in range(K):
                        least[i, k] = min(least[i, k], h[k][own].min())
        there = np.flatnonzero(sizes)
        yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(sizes[there]), pa.array(least[there].tolist(), pa.list_(pa.int64()))], ["set", "size", "h"])

    signed = {r["set"]: r for r in _least(rows.mapInArrow(sign, "set bigint, size bigint, h array<bigint>"), K).collect()}
    kept = [(name, *signed[i][1:]) for name, i in named.items() if i in signed and (delta <= 1 or signed[i]["size"] >= delta)]
    sigs = spark.createDataFrame(kept, "bucket_id string, size bigint, " + ", ".join(f"h{k} bigint" for k in range(K)))
    again = make_bins(sigs, K, 1, 1 if singletons == "keep" else 2, 1, prune=False).select("bin_id", "bucket_id").collect()
    finals, sets = _together(again, named.get)
    counted = [np.unique(own, return_counts=True) for own in sets]
    held_twice = spark.sparkContext.broadcast(Votes(cuts, votes.bins, counted))
    dims = cuts.directions.shape[1]

    def add(batches):
        votes = held_twice.value
        sizes, sums = np.zeros(len(votes.seconds), np.int64), np.zeros((len(votes.seconds), dims), np.int64)
        for ids, x in votes.slices(batches):
            for i, v in enumerate(votes.finals(ids, x)):
                own = np.flatnonzero(v)
                sizes[i] += len(own)
                sums[i] += x[own].sum(0)
        there = np.flatnonzero(sizes)
        yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(sizes[there]), pa.array(sums[there].tolist(), pa.list_(pa.int64()))], ["set", "size", "s"])

    parts = rows.mapInArrow(add, "set bigint, size bigint, s array<bigint>").groupBy("set")
    got = {r["set"]: r for r in parts.agg(F.sum("size").alias("size"), *[F.sum(F.get("s", F.lit(i))).alias(f"s{i}") for i in range(dims)]).collect()}
    seeds = {name: at + 1 for at, name in enumerate(sorted(name for name, i in finals.items() if i in got))}
    mean = lambda total, n: math.floor((2 * total + n) / (2.0 * n))
    centers = [(s, [mean(got[finals[name]][f"s{i}"], got[finals[name]]["size"]) for i in range(dims)], got[finals[name]]["size"]) for name, s in seeds.items()]
    named_sets = [(name, s, finals[name], int(counted[finals[name]][1].sum())) for name, s in seeds.items()]

    def tell(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = _columns(batch)
            found = list(held_twice.value.finals(ids, x))
            for name, s, i, size in named_sets:
                own = np.flatnonzero(found[i])
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name] * len(own), pa.string()), batch.column("id").take(pa.array(own)), pa.array(found[i][own].astype(np.int64)), pa.array(np.full(len(own), size)), pa.array(np.full(len(own), s))],
                    ["group_id", "id", "votes", "bin_size", "seed_id"],
                )

    groups = rows.select("id", "vec").mapInArrow(tell, f"group_id string, id {dict(rows.dtypes)['id']}, votes bigint, bin_size bigint, seed_id bigint")
    return groups, spark.createDataFrame(centers, "seed_id bigint, vec array<bigint>, size bigint")
