"""The compared methods: k-means by Lloyd and by grouped bounds, sample-and-split, k-modes, seeding."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.functions.minhash import estimate_jaccard
from bucketseed.operators.assign import CENTER_BYTES, INDEX_BYTES, SLICE, assign, assign_blocks, collected, members_of, reassign
from bucketseed.operators.centers import centroids, modes
from bucketseed.staging import stage_folder, staged, unstage


#: Draws of k-means++ between two writings of the squared distances.
KEPT = 16


@dataclass
class Fitted:
    """What an iterative method ends with; ``evaluations`` counts row-center distances."""

    centers: np.ndarray
    assigned: DataFrame
    iterations: int
    evaluations: int
    objective: list[float] = field(default_factory=list)
    converged: bool = True


def _numbers(df: DataFrame, vec: str) -> DataFrame:
    """(id, vec) of numbers that workers read as doubles; only other kinds are cast here."""
    plain = dict(df.dtypes)[vec] in ("array<bigint>", "array<int>", "array<double>")
    return df.select("id", (F.col(vec) if plain else F.transform(vec, lambda x: x.cast("double"))).alias("vec"))


def uniform(seed: int, *cols: Column) -> Column:
    """A number in (0, 1) from a hash: the same whenever and wherever a row is computed again."""
    return ((F.shiftrightunsigned(F.xxhash64(F.lit(seed), *cols), 11) + F.lit(0.5)) / F.lit(float(1 << 53))).cast("double")


def random_seeds(df: DataFrame, k: int, seed: int = 0, vec: str = "vec", perms=None) -> DataFrame:
    """(seed_id, vec): the k rows first in a random order, by a top-k and no full sort."""
    order = perms.of(F.col("id"), 0) if perms else F.xxhash64(F.lit(seed), F.col("id"))
    top = df.select("id", vec).orderBy(order, "id").limit(k)
    return top.select(F.col("id").alias("seed_id"), F.col(vec).alias("vec"))


def _to_centers(df: DataFrame, rows: list) -> DataFrame:
    spark = df.sparkSession
    return spark.createDataFrame([(i, [float(x) for x in v]) for i, v in rows], "seed_id bigint, vec array<double>")


def kmeanspp_seeds(df: DataFrame, k: int, seed: int = 0, vec: str = "vec") -> DataFrame:
    """(seed_id, vec) by k sequential draws, each with chance proportional to squared distance.

    A draw is an exponential race: the least -ln(u) / d2 over all rows, one row a task. Squared
    distances are written beside the rows every ``KEPT`` draws; between, the newest centers are compared.
    """
    rows = df.select("id", F.transform(vec, lambda x: x.cast("double")).alias("vec"))
    first = rows.orderBy(F.xxhash64(F.lit(seed), F.col("id")), "id").first()
    chosen = [(first["id"], first["vec"])]
    state, held = rows.withColumn("d2", F.lit(float("inf"))), 0

    def near(batch, c):
        x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
        d2 = batch.column("d2").to_numpy().copy()
        for center in c:
            d2 = np.minimum(d2, ((x - center) ** 2).sum(1))
        return d2

    def update(c):
        def run(batches):
            for batch in batches:
                yield batch.set_column(batch.schema.get_field_index("d2"), "d2", pa.array(near(batch, c)))

        return run

    def race(c):
        def run(batches):
            for batch in batches:
                d2 = near(batch, c)
                with np.errstate(divide="ignore"):
                    w = np.where(d2 > 0, -np.log(batch.column("u").to_numpy()) / d2, np.inf)
                if len(w) and np.isfinite(w.min()):
                    i = int(w.argmin())
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(w[i : i + 1]), batch.column("id")[i : i + 1], batch.column("vec")[i : i + 1]], ["w", "id", "vec"]
                    )

        return run

    kind = dict(rows.dtypes)["id"]
    for turn in range(1, k):
        if len(chosen) - held > KEPT:
            newest = np.array([v for _, v in chosen[held:]])
            state, held = staged(state.mapInArrow(update(newest), state.schema), "kmeanspp"), len(chosen)
        newest = np.array([v for _, v in chosen[held:]])
        drawn = state.withColumn("u", uniform(seed + turn, F.col("id"))).mapInArrow(race(newest), f"w double, id {kind}, vec array<double>")
        best = drawn.agg(F.min(F.struct("w", "id", "vec")).alias("b")).first()["b"]
        if best is None:
            break
        chosen.append((best["id"], best["vec"]))
    return _to_centers(df, chosen)


def _weighted_pp(x: np.ndarray, w: np.ndarray, k: int, rng) -> np.ndarray:
    out = [int(rng.choice(len(x), p=w / w.sum()))]
    d2 = ((x - x[out[0]]) ** 2).sum(1)
    while len(out) < min(k, len(x)) and (w * d2).sum() > 0:
        out.append(int(rng.choice(len(x), p=w * d2 / (w * d2).sum())))
        d2 = np.minimum(d2, ((x - x[out[-1]]) ** 2).sum(1))
    return x[out]


def kmeans_parallel_seeds(df: DataFrame, k: int, rounds: int = 5, factor: float = 2.0, seed: int = 0, vec: str = "vec") -> DataFrame:
    """(seed_id, vec) by few rounds of oversampling, then a weighted reclustering of the candidates.

    Each round samples factor * k rows on average, so the candidates are about rounds * factor * k.
    """
    rows = df.select("id", F.transform(vec, lambda x: x.cast("double")).alias("vec"))
    first = rows.orderBy(F.xxhash64(F.lit(seed), F.col("id")), "id").first()
    found = {first["id"]: first["vec"]}
    for turn in range(1, rounds + 1):
        ids, c = np.array(list(found)), np.array(list(found.values()))
        near = assign_blocks(rows, ids, c)
        cost = near.agg(F.sum(F.col("dist") * F.col("dist"))).first()[0] or 0.0
        if cost <= 0:
            break
        chance = factor * k * F.col("dist") * F.col("dist") / F.lit(cost)
        drawn = near.filter(uniform(seed + turn, F.col("id")) < chance).select("id").join(rows, "id")
        found.update({r["id"]: r["vec"] for r in drawn.collect()})
    ids, c = np.array(list(found)), np.array(list(found.values()))
    weights = {r[0]: r[1] for r in assign_blocks(rows, ids, c).groupBy("cluster_id").count().collect()}
    w = np.array([weights.get(int(i), 0) for i in ids], float) + 1e-9
    best = _weighted_pp(c, w, k, np.random.default_rng(seed))
    return _to_centers(df, list(enumerate(best.tolist())))


def _sums(data: DataFrame, centers: np.ndarray, dist: str = "euclidean") -> tuple[np.ndarray, np.ndarray, float]:
    """Per center: sum and count of its rows, and the squared objective; one row per task and center."""
    held = data.sparkSession.sparkContext.broadcast(centers)

    def run(batches):
        c = held.value
        total, count, cost = np.zeros_like(c), np.zeros(len(c), np.int64), 0.0
        for batch in batches:
            x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, -1)
            for at in range(0, len(x), SLICE):
                part = x[at : at + SLICE]
                d2 = (part * part).sum(1)[:, None] + (c * c).sum(1)[None]
                d2 -= 2 * part @ c.T
                who = np.maximum(d2, 0, out=d2).argmin(1)
                for i in range(x.shape[1]):
                    total[:, i] += np.bincount(who, part[:, i], len(c))
                count += np.bincount(who, minlength=len(c))
                cost += float(d2[np.arange(len(part)), who].sum())
        there = np.flatnonzero(count)
        yield pa.RecordBatch.from_arrays(
            [pa.array(there), pa.array(count[there]), pa.array(total[there].tolist(), pa.list_(pa.float64())), pa.array(np.full(len(there), cost / max(len(there), 1)))],
            ["c", "n", "s", "cost"],
        )

    parts = data.select("vec").mapInArrow(run, "c bigint, n bigint, s array<double>, cost double")
    dims = centers.shape[1]
    rows = parts.groupBy("c").agg(F.sum("n").alias("n"), F.sum("cost").alias("cost"), *[F.sum(F.get("s", F.lit(i))).alias(f"s{i}") for i in range(dims)]).collect()
    total, count, cost = np.zeros_like(centers), np.zeros(len(centers), np.int64), 0.0
    for r in rows:
        total[r["c"]], count[r["c"]] = [r[f"s{i}"] for i in range(dims)], r["n"]
        cost += r["cost"]
    return total, count, cost


def lloyd(df: DataFrame, k: int | None = None, init: DataFrame | None = None, max_iter: int = 20, tol: float = 1e-4, seed: int = 0, vec: str = "vec", exact: bool = False) -> Fitted:
    """Assign and update until centers move less than ``tol``; empty clusters vanish, so k* <= k.

    ``exact`` rounds the means of fixed-point vectors, so that all engines agree; clusters keep the
    ids of their seeds.
    """
    data = _numbers(df, vec)
    ids, c = collected(init if init is not None else random_seeds(data, k, seed), "vec")
    c, n, done, costs, evaluations, settled = c.astype(float), data.count(), 0, [], 0, False
    while done < max_iter and not settled:
        total, count, cost = _sums(data, c)
        evaluations += n * len(c)
        costs.append(cost)
        live = count > 0
        moved = total[live] / count[live][:, None]
        if exact:
            moved = np.floor((2 * total[live] + count[live][:, None]) / (2.0 * count[live][:, None]))
        shift = float(np.abs(moved - c[live]).max()) if live.any() else 0.0
        c, ids, done, settled = moved, ids[live], done + 1, shift <= tol
    return Fitted(c, assign_blocks(data, ids, c), done, evaluations + n * len(c), costs, settled)


def _outwards(bounds: np.ndarray, up: int) -> np.ndarray:
    """Bounds in four bytes, never within what they were."""
    short = bounds.astype(np.float32)
    return np.where((short - bounds) * up < 0, np.nextafter(short, np.float32(np.inf * up)), short)


def yinyang(df: DataFrame, k: int | None = None, init: DataFrame | None = None, groups: int | None = None, max_iter: int = 20, tol: float = 1e-4, seed: int = 0, vec: str = "vec") -> Fitted:
    """Lloyd's result with fewer distances: one upper bound and one lower bound per center group.

    Bounds ride with the rows; a row whose upper bound is below all lower bounds is passed over,
    then groups are, and only the rest is computed. The state of n * groups numbers is the price: bounds are
    written in four bytes, rounded outwards, and a round's go when the next are there.
    """
    data = _numbers(df, vec)
    ids, c = collected(init if init is not None else random_seeds(data, k, seed), "vec")
    c, settled = c.astype(float), False
    groups = groups or max(1, len(c) // 10)
    rng = np.random.default_rng(seed)
    g = c[rng.choice(len(c), groups, replace=False)]
    for _ in range(5):
        who = ((c[:, None] - g[None]) ** 2).sum(-1).argmin(1)
        g = np.array([c[who == j].mean(0) if (who == j).any() else g[j] for j in range(groups)])
    of = who
    dims, evaluations, done = c.shape[1], 0, 0
    schema = f"id bigint, vec {dict(data.dtypes)['vec']}, a int, u float, lows array<float>, work int"
    state = data.select(F.col("id").cast("bigint").alias("id"), "vec", F.lit(-1).alias("a"), F.lit(0.0).cast("float").alias("u"), F.array().cast("array<float>").alias("lows"), F.lit(0).alias("work"))
    before = None
    drift, alive = np.zeros(len(c)), np.ones(len(c), bool)

    def step(held):
        def run(batches):
            c, of, drift, alive = held.value
            most = np.array([drift[(of == j) & alive].max(initial=0.0) for j in range(groups)])
            for batch in batches:
                n = batch.num_rows
                x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(n, -1)
                a = batch.column("a").to_numpy().copy()
                u = batch.column("u").to_numpy().astype(float)
                work = np.zeros(n, np.int64)
                dist = lambda rows, cs: np.sqrt(((x[rows][:, None] - c[cs][None]) ** 2).sum(-1))
                if n and a[0] < 0:
                    low = np.full((n, groups), np.inf)
                    d = np.sqrt(np.maximum((x * x).sum(1)[:, None] + (c * c).sum(1)[None] - 2 * x @ c.T, 0))
                    a = d.argmin(1)
                    u = d[np.arange(n), a]
                    d[np.arange(n), a] = np.inf
                    for j in range(groups):
                        cols = of == j
                        if cols.any():
                            low[:, j] = d[:, cols].min(1)
                    work += len(c)
                elif n:
                    low = batch.column("lows").flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(float)
                    low -= most[None]
                    gone = ~alive[a]
                    u = np.where(gone, np.inf, u + drift[a])
                    open_ = np.flatnonzero(u >= low.min(1))
                    fine = open_[~gone[open_]]
                    u[fine] = np.sqrt(((x[fine] - c[a[fine]]) ** 2).sum(1))
                    work[fine] += 1
                    open_ = open_[u[open_] >= low[open_].min(1)]
                    old_a = a.copy()
                    for j in range(groups):
                        cols = np.flatnonzero((of == j) & alive)
                        rows = open_[(low[open_, j] <= u[open_])]
                        if not len(cols) or not len(rows):
                            continue
                        d = dist(rows, cols)
                        work[rows] += len(cols)
                        own = cols[None] == old_a[rows][:, None]
                        d = np.where(own, np.inf, d)
                        i = d.argmin(1)
                        v = d[np.arange(len(rows)), i]
                        low[rows, j] = v
                        tie = (v == u[rows]) & (cols[i] < a[rows])
                        better = (v < u[rows]) | tie
                        # the center left behind bounds its own group
                        r, left = rows[better], of[a[rows[better]]]
                        low[r, left] = np.minimum(low[r, left], u[r])
                        second = np.partition(d[better], 1, axis=1)[:, 1] if d.shape[1] > 1 else np.full(len(r), np.inf)
                        low[r, j] = np.where(left == j, np.minimum(second, u[r]), second)
                        a[r], u[r] = cols[i[better]], v[better]
                else:
                    low = np.zeros((0, groups))
                offs = lambda w: pa.array(np.arange(n + 1, dtype=np.int32) * w)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("id"), batch.column("vec"), pa.array(a.astype(np.int32)), pa.array(_outwards(u, 1)), pa.ListArray.from_arrays(offs(groups), pa.array(_outwards(low.ravel(), -1))), pa.array(work.astype(np.int32))],
                    ["id", "vec", "a", "u", "lows", "work"],
                )
        return run

    while done < max_iter and not settled:
        held = df.sparkSession.sparkContext.broadcast((c, of, drift, alive))
        state, last = state.mapInArrow(step(held), schema), before
        before = stage_folder(state, "bounds")
        state = df.sparkSession.read.schema(state.schema).parquet(before)
        sums = state.groupBy("a").agg(F.count("*").alias("n"), F.sum("work").alias("work"), *[F.sum(F.get("vec", F.lit(i))).alias(f"s{i}") for i in range(dims)]).collect()
        evaluations += sum(r["work"] for r in sums)
        if last:
            unstage(df.sparkSession, last)
        moved, seen = c.copy(), np.zeros(len(c), bool)
        for r in sums:
            moved[r["a"]] = np.array([r[f"s{i}"] for i in range(dims)]) / r["n"]
            seen[r["a"]] = True
        drift = np.sqrt(((moved - c) ** 2).sum(1))
        shift = float(np.abs(moved - c)[seen].max())
        alive = alive & seen
        c, done, settled = moved, done + 1, shift <= tol
    if before:
        unstage(df.sparkSession, before)
    c = c[alive]
    evaluations += data.count() * len(c)
    return Fitted(c, assign_blocks(data, ids[alive], c), done, evaluations, [], settled)


def sampled_kmeans(df: DataFrame, k: int, per_center: int = 256, split: bool = True, max_iter: int = 20, tol: float = 1e-4, seed: int = 0, vec: str = "vec") -> Fitted:
    """Train on per_center * k rows (on average, by a threshold on the id's hash), refill empty
    clusters by splitting the largest (so k* = k), then assign all rows once."""
    data = _numbers(df, vec)
    n_all, settled, done = data.count(), False, 0
    sample = staged(data.filter(uniform(seed, F.col("id")) < per_center * k / max(n_all, 1)), "sample")
    _, c = collected(random_seeds(sample, k, seed + 1), "vec")
    c, evaluations, n = c.astype(float), 0, sample.count()
    while done < max_iter and not settled:
        total, count, _ = _sums(sample, c)
        evaluations += n * len(c)
        live, before = count > 0, c.copy()
        c[live] = total[live] / count[live][:, None]
        done, settled = done + 1, bool(live.all()) and float(np.abs(c - before).max()) <= tol
        if split:
            for j in np.flatnonzero(~live):
                big = int(count.argmax())
                c[j] = c[big] * (1 + 1 / 1024) + 1e-9
                c[big] = c[big] * (1 - 1 / 1024) - 1e-9
                count[j] = count[big] // 2
                count[big] -= count[j]
    return Fitted(c, assign_blocks(data, np.arange(len(c)), c), done, evaluations + n_all * len(c), [], settled)


class _Nearest:
    """Assignments to centers that move, and the rows they are made for; ``work`` counts row-center comparisons.

    Rows are dealt by id once, so that the last assignment, and groups of ids, meet them where they are.
    """

    def __init__(self, data: DataFrame, exact: bool):
        spark, self.exact = data.sparkSession, exact
        reach = F.greatest(F.abs(F.array_max("tokens")), F.abs(F.array_min("tokens")))
        if (data.agg(F.max(reach)).first()[0] or 0) < 1 << 31:
            data = data.withColumn("tokens", F.col("tokens").cast("array<int>"))
        parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.rows = data.repartition(parts, "id").sortWithinPartitions("id").persist(StorageLevel.DISK_ONLY)
        self.n, self.work, self.last, self.known = self.rows.count(), 0, None, None

    def __call__(self, centers: DataFrame) -> DataFrame:
        size = centers.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size("modes")), F.lit(1)).alias("dims")).first()
        if self.exact or 8 * size["n"] * size["dims"] > min(CENTER_BYTES, INDEX_BYTES):
            wide = self.rows.withColumn("tokens", F.col("tokens").cast("array<bigint>"))
            out, self.known = assign(wide, centers, "jaccard_tokens", "sql" if self.exact else "gemm", "tokens", "modes"), None
            out = out.withColumns({"was": F.lit(None).cast("bigint"), "m": F.lit(0), "work": F.lit(size["n"]).cast("bigint")})
            if self.last is not None:
                out = out.drop("was").join(self.last.select("id", F.col("cluster_id").alias("was")), "id")
        else:
            ids, c = collected(centers, "modes")
            changed = np.ones(len(ids), bool)
            if self.known:
                at = np.minimum(np.searchsorted(self.known[0], ids), len(self.known[0]) - 1)
                changed = (self.known[0][at] != ids) | (self.known[1][at] != c).any(1)
            if self.last is None:
                rows = self.rows.withColumns({"was": F.lit(None).cast("bigint"), "m": F.lit(0)})
            else:
                # without the centers before, no row's last one bounds the others
                bound = F.col("m") if self.known else F.lit(1 << 30)
                rows = self.rows.join(self.last.select("id", F.col("cluster_id").alias("was"), bound.alias("m")), "id")
            out, self.known = reassign(rows, ids, c, changed), (ids, c)
        self.last = staged(out, "kmodes")
        self.work += self.last.agg(F.sum("work")).first()[0] or 0
        return self.last


def kmodes(df: DataFrame, k: int | None = None, init: DataFrame | None = None, max_iter: int = 20, seed: int = 0, tokens: str = "tokens", exact: bool = False) -> Fitted:
    """Assign by equal coordinates and move to modes until no row changes; empty clusters vanish."""
    data = df.select("id", F.col(tokens).alias("tokens"))
    centers = init if init is not None else random_seeds(data, k, seed, "tokens").select("seed_id", F.col("vec").alias("modes"))
    near, done, settled = _Nearest(data, exact), 0, False
    out, touched = near(centers), None
    while done < max_iter and not settled:
        members = members_of(out)
        if touched is None:
            centers = staged(modes(members, near.rows).select("seed_id", "modes"), "modes")
        else:
            # Clusters that no row left or joined keep their modes.
            moved = modes(members.join(touched, "seed_id", "left_semi"), near.rows).select("seed_id", "modes")
            centers = staged(centers.join(touched, "seed_id", "left_anti").unionByName(moved), "modes")
        out, done = near(centers), done + 1
        touched = staged(out.filter("cluster_id <> was").select(F.explode(F.array("cluster_id", "was")).alias("seed_id")).distinct(), "touched")
        settled = not touched.take(1)
    _, c = collected(centers, "modes")
    near.rows.unpersist()
    return Fitted(c, out.select("id", "cluster_id", "dist"), done, near.work, [], settled)


def mllib_kmeans(df: DataFrame, k: int, seed: int = 0, bisecting: bool = False, vec: str = "vec") -> DataFrame:
    """(id, cluster_id) of Spark's own k-means: an independent check."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    data = df.select("id", array_to_vector(F.transform(vec, lambda x: x.cast("double"))).alias("features"))
    model = (BisectingKMeans if bisecting else KMeans)(k=k, seed=seed).fit(data)
    return model.transform(data).select("id", F.col("prediction").cast("bigint").alias("cluster_id"))


def seed_eval(df: DataFrame, centers: DataFrame, vec: str = "vec") -> DataFrame:
    """One assignment to the seeds of any seeding method."""
    return assign(df, centers, vec=vec)


def lsh_bisect(df: DataFrame, sketch: str, levels: int = 3, seed: int = 0) -> DataFrame:
    """(id, cluster_id): repeated two-way splits by estimated similarity to two far members."""
    out = df.select("id", sketch, F.lit(1).cast("bigint").alias("cluster_id"))
    for _ in range(levels):
        out = staged(out, "bisect")
        poles = out.groupBy("cluster_id").agg(F.min(F.struct(F.xxhash64(F.lit(seed), F.col("id")).alias("h"), sketch)).alias("p"))
        near = out.join(poles, "cluster_id").withColumn("s", estimate_jaccard(F.col(sketch), F.col(f"p.{sketch}")))
        far = near.groupBy("cluster_id").agg(F.min(F.struct("s", "id", sketch)).alias("q"))
        out = near.join(far, "cluster_id").select(
            "id", sketch,
            (F.col("cluster_id") * 2 + (estimate_jaccard(F.col(sketch), F.col(f"q.{sketch}")) > F.col("s")).cast("bigint")).alias("cluster_id"),
        )
    return out.select("id", "cluster_id")


def lsh_partition_cluster(df: DataFrame, k_local: int, parts: int = 8, seed: int = 0, vec: str = "vec", direction=None) -> DataFrame:
    """(id, cluster_id): near rows on one worker by a projection's quantile, clustered there, merged.

    Each part takes its own k-means on the worker; parts' centers are merged when one is another's
    nearest and the other's too.
    """
    from bucketseed.functions.projection import dot, gaussian

    dims = len(df.select(vec).first()[0])
    direction = direction or gaussian(1, dims, seed)[0].tolist()
    rows = df.select("id", F.transform(vec, lambda x: x.cast("double")).alias("vec")).withColumn("h", dot("vec", direction))
    cuts = rows.approxQuantile("h", [i / parts for i in range(1, parts)], 0.01)
    part = sum(((F.col("h") > F.lit(c)).cast("int") for c in cuts), F.lit(0))

    def local(pdf):
        x = np.stack(pdf["vec"].to_numpy())
        rng = np.random.default_rng(seed)
        c = _weighted_pp(x, np.ones(len(x)), k_local, rng)
        for _ in range(10):
            who = ((x[:, None] - c[None]) ** 2).sum(-1).argmin(1)
            c = np.array([x[who == j].mean(0) if (who == j).any() else c[j] for j in range(len(c))])
        pdf["cluster_id"] = pdf["part"].astype("int64") * k_local + who
        return pdf[["id", "cluster_id"]]

    found = staged(rows.withColumn("part", part).groupBy("part").applyInPandas(local, "id bigint, cluster_id bigint"), "local")
    means = centroids(members_of(found), rows, "vec", dims, exact=False)
    ids, c = collected(means, "vec")
    d = ((c[:, None] - c[None]) ** 2).sum(-1)
    np.fill_diagonal(d, math.inf)
    near = d.argmin(1)
    merged = {int(ids[i]): int(min(ids[i], ids[near[i]])) if near[near[i]] == i and ids[i] // k_local != ids[near[i]] // k_local else int(ids[i]) for i in range(len(ids))}
    names = df.sparkSession.createDataFrame(list(merged.items()), "cluster_id bigint, final bigint")
    return found.join(F.broadcast(names), "cluster_id").select("id", F.col("final").alias("cluster_id"))
