"""MinHash near-duplicates: one-permutation hashing with optimal densification.

A text's set is its distinct 5-word shingles as 64-bit hashes. One pass over the set fills ``BINS``
bins with minima; an empty bin takes the value of the first full bin in an order of its own that
all texts share. Equal sets collapse first. Sketches of one text per set go to banded buckets;
every bucket proposes a star, from one centre to its members, so candidate pairs are at most as
many as bucket rows. Candidates are confirmed on full sets. As a member may resemble another
member but not the centre, buckets that still join different components propose further stars
around other centres, while many of the pairs are links. What the stars left is then settled exactly:
members of buckets that still join different components meet in a join over prefixes of their full
sets, which passes over no pair at the threshold.

Chance of missing a pair: at similarity 0.75 two sets share no band with probability
(1 - 0.75^5)^51 < 2e-6 (each band alone); pairs that share one are all decided. Defined results: null or empty text and null ids have no links and stand alone; fewer
than five words are one shingle; repeated rows give a row each, and rows of one id are one node;
a tie for the representative goes to the smallest id; ids may be of any orderable type; very long
texts are read whole, one at a time; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bucketseed.llm.components import components
from bucketseed.llm.hashing import list_array, mix, pieces, shingle_hashes, uniques, word_hashes
from bucketseed.staging import counted, staged

BINS, ROWS = 256, 5
BANDS = BINS // ROWS
SHINGLE = 5
#: Tables of ids, pairs and labels are broadcast only up to this many rows (32 bytes at most each).
BROADCAST_IDS = 500_000
#: Rounds of stars go on while this share of their pairs are links; an exact join decides the rest.
FRUITFUL = 0.1

_ORDER = np.argsort(
    np.random.default_rng(20).permuted(np.tile(np.arange(BINS), (BINS, 1)), axis=1), axis=1
).astype(np.uint16)
_ODD = mix(np.arange(1, ROWS + 1, dtype=np.uint64)) | np.uint64(1)
_SALT = mix(np.arange(100, 100 + BANDS, dtype=np.uint64))


def sketch(sorted_set: np.ndarray) -> np.ndarray:
    """BINS values of a non-empty set: the least hash of each bin, borrowed where a bin is empty."""
    bins = (sorted_set >> np.uint64(56)).astype(np.int64)
    at = np.flatnonzero(np.concatenate([[True], bins[1:] != bins[:-1]]))
    full, values = bins[at], sorted_set[at]
    out = np.empty(BINS, np.uint64)
    out[full] = values
    if len(full) < BINS:
        empty = np.ones(BINS, bool)
        empty[full] = False
        empty = np.flatnonzero(empty)
        out[empty] = values[_ORDER[np.ix_(empty, full)].argmin(1)]
    return out


def band_keys(values: np.ndarray) -> np.ndarray:
    return mix((values[: BANDS * ROWS].reshape(BANDS, ROWS) * _ODD).sum(1) + _SALT)


def shingle_sets(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return uniques(*shingle_hashes(*word_hashes(data, offs), SHINGLE))


def sketched(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, set_hash, bands) of every row."""

    def run(batches):
        for batch, data, offs in pieces(batches):
            sets, first = shingle_sets(data, offs)
            keys, sums = [], []
            for a, b in zip(first[:-1], first[1:], strict=True):
                keys.append(band_keys(sketch(sets[a:b])) if b > a else sets[:0])
                sums.append(mix(mix(sets[a:b]).sum(keepdims=True))[0] if b > a else np.uint64(0))
            begin = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id").cast(pa.int64()),
                    pa.array(np.diff(first), pa.int64()),
                    pa.array(np.array(sums, np.uint64).view(np.int64)),
                    list_array(np.concatenate(keys), begin),
                ],
                ["doc_id", "n_shingles", "set_hash", "bands"],
            )

    return docs.select("doc_id", F.col(text).alias("text")).mapInArrow(
        run, "doc_id bigint, n_shingles bigint, set_hash bigint, bands array<bigint>"
    )


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Those (a, b) of ``pairs`` whose full sets overlap by ``percent`` or more."""

    def run(batches):
        for batch, data, offs in pieces(batches, "ta"):
            left, lf = shingle_sets(data, offs)
            i, good = 0, []
            for _, other, at in pieces(iter([batch]), "tb"):
                right, rf = shingle_sets(other, at)
                for j in range(len(at) - 1):
                    x, y = left[lf[i] : lf[i + 1]], right[rf[j] : rf[j + 1]]
                    low, high = sorted((len(x), len(y)))
                    same = 0
                    if 100 * low >= percent * high > 0:
                        same = len(np.intersect1d(x, y, assume_unique=True))
                    good.append(same > 0 and 100 * same >= percent * (low + high - same))
                    i += 1
            yield pa.RecordBatch.from_arrays(
                [batch.column("a"), batch.column("b"), pa.array(good, pa.bool_())], ["a", "b", "good"]
            )

    one = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta"))
    two = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb"))
    return (
        pairs.join(one, "a")
        .join(two, "b")
        .select("a", "b", "ta", "tb")
        .mapInArrow(run, "a bigint, b bigint, good boolean")
        .filter("good")
        .select("a", "b")
        .distinct()
    )


def _sized(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_IDS else df


def shingles(texts: DataFrame) -> DataFrame:
    """(doc_id, shingles) of every row: its set as an array of hashes."""

    def run(batches):
        for batch, data, offs in pieces(batches):
            sets, first = shingle_sets(data, offs)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), list_array(sets, first)], ["doc_id", "shingles"]
            )

    return texts.select("doc_id", "text").mapInArrow(run, "doc_id bigint, shingles array<bigint>")


def prefix_pairs(open_ids: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of ``open_ids`` (doc_id, comp, n) from different components that may be similar.

    Shingles of one component only come first in an order that all sets share, then rare ones. Two
    sets that overlap by ``percent`` share one of the first n - ceil(n percent / 100) + 1 of each,
    and at the first one they share, what follows in either set leaves room for the overlap.
    """
    held, _ = counted(
        shingles(texts).join(open_ids, "doc_id").select("doc_id", "comp", "n", F.explode("shingles").alias("s")),
        "shingles",
    )
    wide = (
        held.groupBy("s")
        .agg(F.count("*").alias("df"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
        .filter("lo < hi")
        .select("s", "df")
    )
    common, _ = counted(held.join(wide, "s"), "common")
    own = F.col("n") - F.count("*").over(Window.partitionBy("doc_id"))
    place = F.row_number().over(Window.partitionBy("doc_id").orderBy("df", "s"))
    prefix, _ = counted(
        common.select("*", (own + place).alias("at"))
        .filter(F.col("at") <= F.col("n") - F.ceil(F.col("n") * percent / 100) + 1)
        .select("s", "doc_id", "comp", "n", (F.col("n") - F.col("at") + 1).alias("room")),
        "prefixes",
    )
    other = prefix.select(
        "s", F.col("doc_id").alias("b"), F.col("comp").alias("bcomp"), F.col("n").alias("bn"), F.col("room").alias("broom")
    )
    overlap = (100 + percent) * F.least("room", "broom") >= percent * (F.col("n") + F.col("bn"))
    apart = (F.col("doc_id") < F.col("b")) & (F.col("comp") != F.col("bcomp"))
    return prefix.join(other, (prefix["s"] == other["s"]) & apart & overlap).select(F.col("doc_id").alias("a"), "b").distinct()


def near_duplicates(docs: DataFrame, text: str = "text", percent: int = 75) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row."""
    if dict(docs.dtypes)["doc_id"] not in ("tinyint", "smallint", "int", "bigint"):
        return near_duplicates_any_id(docs, text, percent)
    rows = staged(sketched(docs, text), "sketches")
    real = rows.filter("n_shingles > 0 AND doc_id IS NOT NULL")
    sets = staged(
        real.groupBy("set_hash", "n_shingles").agg(F.min("doc_id").alias("rep")), "sets"
    )
    banded = real.join(
        sets.select("set_hash", "n_shingles", F.col("rep").alias("doc_id")),
        ["set_hash", "n_shingles", "doc_id"],
        "left_semi",
    ).select("doc_id", F.explode("bands").alias("key"))
    shared = (
        banded.groupBy("key")
        .agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"))
        .filter("low < high")
        .select("key", F.col("low").alias("center"))
    )
    members = staged(banded.join(shared, "key"), "buckets")

    ids = staged(members.select("doc_id").distinct(), "candidates")
    texts = staged(
        docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col(text).alias("text")).join(
            _sized(ids, ids.count()), "doc_id", "left_semi"
        ),
        "texts",
    )
    pairs = members.filter("center <> doc_id").select(F.col("center").alias("a"), F.col("doc_id").alias("b"))
    tried, n = counted(pairs.distinct(), "pairs")
    links, _ = counted(confirmed(_sized(tried, n), texts, percent), "links")
    comps, turn = components(links), 0

    def placed() -> DataFrame:
        return members.join(
            _sized(comps, comps.count()), F.col("doc_id") == F.col("node"), "left"
        ).select("key", "doc_id", F.coalesce("comp", "doc_id").alias("comp"))

    while True:
        turn += 1
        now = placed().withColumn("h", F.xxhash64("doc_id", F.lit(turn)))
        centers, n = counted(
            now.groupBy("key")
            .agg(F.min(F.struct("h", "doc_id", "comp")).alias("c"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
            .filter("lo < hi")
            .select("key", F.col("c.doc_id").alias("center"), F.col("c.comp").alias("ccomp")),
            "centers",
        )
        if not n:
            break
        fresh, n = counted(
            now.join(_sized(centers, n), "key")
            .filter(F.col("comp") != F.col("ccomp"))
            .select(F.least("center", "doc_id").alias("a"), F.greatest("center", "doc_id").alias("b"))
            .distinct()
            .join(tried, ["a", "b"], "left_anti"),
            "pairs",
        )
        if not n:
            break
        tried = tried.unionByName(fresh)
        found, new = counted(confirmed(_sized(fresh, n), texts, percent), "links")
        if new:
            links = links.unionByName(found)
            comps = components(links)
        if new < FRUITFUL * n:
            break

    # Stars that find little prove nothing for the other members: those are settled exactly.
    now = placed()
    unsettled, n = counted(
        now.groupBy("key").agg(F.count("*").alias("size"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
        # the stars tried the pair of a bucket of two
        .filter("lo < hi AND size > 2")
        .select("key"),
        "unsettled",
    )
    if n:
        sizes = sets.select(F.col("rep").alias("doc_id"), F.col("n_shingles").alias("n"))
        left = now.join(_sized(unsettled, n), "key", "left_semi").select("doc_id", "comp").distinct()
        open_ids, n = counted(left.join(sizes, "doc_id"), "unsettled")
        pairs = prefix_pairs(_sized(open_ids, n), texts.join(_sized(open_ids, n), "doc_id", "left_semi"), percent)
        fresh, n = counted(pairs.join(tried, ["a", "b"], "left_anti"), "pairs")
        found, new = counted(confirmed(_sized(fresh, n), texts, percent), "links")
        if new:
            comps = components(links.unionByName(found))

    return (
        rows.join(sets, ["set_hash", "n_shingles"], "left")
        .join(comps, F.col("rep") == F.col("node"), "left")
        .select(
            "doc_id",
            "n_shingles",
            F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.coalesce("comp", "rep"))
            .otherwise(F.col("doc_id"))
            .alias("component_id"),
        )
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def _by_row(rows: DataFrame, percent: int) -> DataFrame:
    """(_row, n_shingles, _comp): components of rows (_row, text) as nodes, whatever their ids."""
    found = near_duplicates(rows.select(F.col("_row").alias("doc_id"), "text"), "text", percent)
    return found.select(F.col("doc_id").alias("_row"), "n_shingles", F.col("component_id").alias("_comp"))


def near_duplicates_any_id(docs: DataFrame, text: str = "text", percent: int = 75) -> DataFrame:
    """``near_duplicates`` for ids of any orderable type, such as strings; rows are the nodes.

    Null ids stand alone. The component is named by its smallest id.
    """
    rows = staged(
        docs.select(
            F.monotonically_increasing_id().alias("_row"),
            "doc_id",
            F.when(F.col("doc_id").isNotNull(), F.col(text)).alias("text"),
        ),
        "rows",
    )
    placed = staged(rows.select("_row", "doc_id").join(_by_row(rows, percent), "_row"), "placed")
    least = placed.groupBy("_comp").agg(F.min("doc_id").alias("component_id"))
    return placed.join(least, "_comp").select(
        "doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept")
    )


def one_of_each(docs: DataFrame, text: str = "text", percent: int = 75) -> DataFrame:
    """The rows of ``docs`` without near duplicates: of each group the row of the smallest id stays.

    Rows are judged, not ids: rows that share an id or have none go only if their text resembles
    another row's. A row without an id stands behind all others, then the earlier row stays.
    """
    rows = staged(docs.select("*", F.monotonically_increasing_id().alias("_row")), "rows")
    placed = staged(
        rows.select("_row", F.col("doc_id").alias("_id")).join(
            _by_row(rows.select("_row", F.col(text).alias("text")), percent), "_row"
        ),
        "placed",
    )
    shared = placed.groupBy("_comp").agg(
        F.count("*").alias("_n"), F.min(F.struct(F.col("_id").isNull().alias("none"), "_id", "_row")).alias("_first")
    )
    gone, n = counted(
        placed.join(shared.filter("_n > 1"), "_comp").filter("_row <> _first._row").select("_row"), "gone"
    )
    return rows.join(_sized(gone, n), "_row", "left_anti").select(docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    return near_duplicates(load(spark, sf_dir, "documents"))


_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOW}, '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS (
  SELECT DISTINCT doc_id, array_to_string(ws[i:i+4], ' ') AS k
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM d WHERE len(ws) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
s AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.k = b.k AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT s.a, s.b FROM s JOIN n x ON x.doc_id = s.a JOIN n y ON y.doc_id = s.b
      WHERE 100 * s.c >= 75 * (x.n + y.n - s.c)),
r AS (SELECT doc_id, doc_id AS c FROM d UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.doc_id),
m AS (SELECT doc_id, min(c) AS component_id FROM r GROUP BY doc_id)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.component_id, d.doc_id = m.component_id AS kept
FROM d JOIN m ON m.doc_id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""
