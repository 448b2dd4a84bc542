"""Uses of many small clusters: summaries, hierarchies, density, and indexed search.

Clusters of this method are compact and roughly round; shapes and dendrograms come from working on
the micro-clusters, as ``hierarchy`` and ``density`` do.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.functions.distances import l2
from bucketseed.operators.assign import collected, members_of
from bucketseed.operators.centers import centroids
from bucketseed.operators.ranking import ranked
from bucketseed.staging import staged


def summarise(assigned: DataFrame, data: DataFrame, vec: str = "vec", dims: int | None = None, exact: bool = True) -> DataFrame:
    """(cluster_id, vec, size, radius, total): the members' mean and spread."""
    means = centroids(members_of(assigned), data, vec, dims, exact)
    spread = assigned.groupBy("cluster_id").agg(F.max("dist").alias("radius"), F.sum("dist").alias("total"))
    return means.withColumnRenamed("seed_id", "cluster_id").join(spread, "cluster_id")


def hierarchy(micro: DataFrame, clusters: int, link: str = "average") -> DataFrame:
    """(cluster_id, parent): agglomerative merging of the centers (they must fit one machine)."""
    ids, c = collected(micro.withColumnRenamed("cluster_id", "seed_id"), "vec")
    if len(ids) > 20_000:
        raise ValueError("too many micro-clusters for one machine; summarise them again first")
    c = c.astype(float)
    d = np.sqrt(np.maximum(((c[:, None] - c[None]) ** 2).sum(-1), 0)) if len(c) else np.zeros((0, 0))
    np.fill_diagonal(d, np.inf)
    size, parent = np.ones(len(c)), np.arange(len(c))
    for _ in range(max(0, len(c) - clusters)):
        i, j = np.unravel_index(d.argmin(), d.shape)
        i, j = min(i, j), max(i, j)
        merged = np.maximum(d[i], d[j]) if link == "complete" else (size[i] * d[i] + size[j] * d[j]) / (size[i] + size[j])
        d[i], d[:, i] = merged, merged
        d[i, i] = np.inf
        d[j], d[:, j] = np.inf, np.inf
        size[i] += size[j]
        parent[parent == j] = i
    rows = [(int(a), int(ids[p])) for a, p in zip(ids, parent, strict=True)]
    return micro.sparkSession.createDataFrame(rows, "cluster_id bigint, parent bigint")


def density(micro: DataFrame, eps: float, min_size: int) -> DataFrame:
    """(cluster_id, component): dense micro-clusters within ``eps`` of one another, -1 for the rest."""
    dense = staged(micro.filter(F.col("size") >= min_size).select("cluster_id", "vec"), "dense")
    other = dense.select(F.col("cluster_id").alias("other"), F.col("vec").alias("ovec"))
    arcs = staged(dense.join(other, F.col("cluster_id") != F.col("other")).filter(l2("vec", "ovec") <= eps).select("cluster_id", "other"), "arcs")
    labels = dense.select("cluster_id", F.col("cluster_id").alias("component"))
    while True:
        near = arcs.join(labels.withColumnsRenamed({"cluster_id": "other", "component": "near"}), "other").groupBy("cluster_id").agg(F.min("near").alias("near"))
        after = staged(labels.join(near, "cluster_id", "left").select("cluster_id", F.least("component", F.coalesce("near", "component")).alias("component"), F.col("component").alias("was")), "labels")
        labels = after.select("cluster_id", "component")
        if after.filter("component <> was").isEmpty():
            break
    return micro.select("cluster_id").join(labels, "cluster_id", "left").select("cluster_id", F.coalesce("component", F.lit(-1).cast("bigint")).alias("component"))


def search(micro: DataFrame, assigned: DataFrame, data: DataFrame, queries: DataFrame, probes: int, top: int, vec: str = "vec") -> DataFrame:
    """(qid, id, dist, rank): members of each query's nearest clusters, by exact distance."""
    c = F.broadcast(micro.select("cluster_id", F.col("vec").alias("_c")))
    near = queries.crossJoin(c).withColumn("cd", l2(F.col(vec), F.col("_c")))
    w = Window.partitionBy("qid").orderBy("cd", "cluster_id")
    probed = near.withColumn("p", F.row_number().over(w)).filter(F.col("p") <= probes).select("qid", F.col(vec).alias("_q"), "cluster_id")
    rows = assigned.select("id", "cluster_id").join(data.select("id", F.col(vec).alias("_v")), "id")
    found = probed.join(rows, "cluster_id").select("qid", "id", l2(F.col("_q"), F.col("_v")).alias("dist"))
    r = Window.partitionBy("qid").orderBy("dist", "id")
    return found.withColumn("rank", F.row_number().over(r)).filter(F.col("rank") <= top)


#: Vectors' coordinates that are broadcast at once, and distances that are held at once.
CHUNK_CELLS = 8_000_000
DISTANCES = 4_000_000


def range_search(micro: DataFrame, assigned: DataFrame, data: DataFrame, queries: DataFrame, eps: float, vec: str = "vec") -> DataFrame:
    """(qid, id, dist) of all rows within ``eps``; clusters whose ball can't reach are passed over.

    Needs ``radius`` measured from the same centers. Queries are broadcast in chunks; rows meet them where
    they are read. Matrix products only choose, with room for their rounding: what they leave is measured
    coordinate by coordinate, in the columns' order.
    """
    places = {c: dict(df.dtypes)[c] for df, c in ((queries, "qid"), (data, "id"))}
    schema = f"qid {places['qid']}, id {places['id']}, dist double"
    balls = micro.select("cluster_id", F.col(vec).alias("_c"), "radius").toArrow().combine_chunks().sort_by("cluster_id")
    names, radius = balls["cluster_id"].to_numpy(), balls["radius"].to_numpy()
    wide = lambda column, n: column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 0))
    c = wide(balls["_c"], len(names))
    rows = assigned.select("id", "cluster_id").join(data.select("id", F.col(vec).alias("_v")), "id")
    n = queries.count()
    per = max(1, CHUNK_CELLS // max(1, c.shape[1]))
    parts = [queries.select("qid", vec)]
    if n > per:
        placed = ranked(queries, ["qid"], ["qid", vec])
        parts = [placed.filter(F.col("rank").between(at, at + per - 1)).select("qid", vec) for at in range(0, n, per)]
    out = None
    for part in parts:
        table = part.toArrow()
        held = micro.sparkSession.sparkContext.broadcast((table["qid"].combine_chunks(), wide(table[vec], table.num_rows), names, c, radius))
        found = rows.mapInArrow(_within(held, eps), schema)
        out = found if out is None else out.unionByName(found)
    return out


def _within(held, eps: float):
    def run(batches):
        qids, q, names, c, radius = held.value
        if not len(qids) or not len(names):
            return
        about, least = q.astype(float), (q * q).astype(float).sum(1)
        slack = lambda x, y: 1e-9 * (x + y) + 1e-6
        own, size = c.astype(float), (c.astype(float) ** 2).sum(1)
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            v = batch.column("_v").flatten().to_numpy(zero_copy_only=False).reshape(n, -1)
            x = v.astype(float)
            x2 = (x * x).sum(1)
            cluster = batch.column("cluster_id").to_numpy(zero_copy_only=False)
            order = np.argsort(cluster, kind="stable")
            found, first = np.unique(cluster[order], return_index=True)
            of = np.minimum(np.searchsorted(names, found), len(names) - 1)
            known = names[of] == found  # a row without a center of its cluster is in no ball
            step = max(1, DISTANCES // len(qids))
            for at in range(0, n, step):
                some = order[at : at + step]
                here = np.flatnonzero((first < at + len(some)) & (np.append(first[1:], n) > at) & known)
                near = np.zeros(len(qids), bool)
                for j in range(0, len(here), step):
                    ball = of[here[j : j + step]]
                    reach = least[:, None] + size[ball][None] - 2 * about @ own[ball].T
                    near |= (reach <= (eps + radius[ball][None]) ** 2 + slack(least[:, None], size[ball][None])).any(1)
                near = np.flatnonzero(near)
                some = some[np.isin(cluster[some], found[here])]
                if len(near) and len(some):
                    d2 = least[near][:, None] + x2[some][None] - 2 * about[near] @ x[some].T
                    a, b = np.nonzero(d2 <= eps * eps + slack(least[near][:, None], x2[some][None]))
                    for part in range(0, len(a), 65_536):
                        i, j = near[a[part : part + 65_536]], some[b[part : part + 65_536]]
                        total = np.zeros(len(i))
                        for y in range(q.shape[1]):
                            gap = q[i, y] - v[j, y]
                            total += (gap * gap).astype(float)
                        dist = np.sqrt(total)
                        good = np.flatnonzero(dist <= eps)
                        yield pa.RecordBatch.from_arrays(
                            [qids.take(pa.array(i[good])), batch.column("id").take(pa.array(j[good])), pa.array(dist[good])], ["qid", "id", "dist"]
                        )

    return run
