"""DuckDB twins: SQL pieces rendered from the same parameters that the queries use."""

from __future__ import annotations

from bucketseed.functions.doph import width_of
from bucketseed.functions.features import LETTERS
from bucketseed.functions.permutations import Permutations, affine_perms

WORDS = (
    r"list_sort(list_distinct(list_transform(list_filter(string_split_regex(lower(coalesce({text}, '')), '\s+'), "
    r"lambda w: w <> ''), lambda w: ('0x' || substr(md5(w), 1, 7))::BIGINT)))"
)


def token(expr: str) -> str:
    return f"(('0x' || substr(md5({expr}), 1, 7))::BIGINT)"


def with_(ctes: dict[str, str], final: str) -> str:
    return "WITH " + ",\n".join(f"{k} AS ({v})" for k, v in ctes.items()) + "\n" + final


def docs_sets() -> dict[str, str]:
    return {"sets": f"SELECT doc_id AS id, {WORDS.format(text='text')} AS tokens FROM documents"}


def page_sets() -> dict[str, str]:
    text = "regexp_replace(coalesce(html, ''), '<[^>]*>', ' ', 'g')"
    return {"sets": f"SELECT page_id AS id, {WORDS.format(text=text)} AS tokens FROM pages"}


def turn_sets() -> dict[str, str]:
    return {"sets": f"SELECT conv_id * 1000 + turn AS id, {WORDS.format(text='text')} AS tokens FROM conversations"}


def basket_sets() -> dict[str, str]:
    return {
        "sets": "SELECT o_custkey AS id, list_sort(list_distinct(list(l_partkey))) AS tokens "
        "FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY o_custkey"
    }


def embedding_rows() -> dict[str, str]:
    return {
        "data": "SELECT vec_id AS id, list_transform(embedding, lambda x: floor(x::DOUBLE * 1000000.0 + 0.5)::BIGINT) AS vec FROM embeddings"
    }


LINEITEM_ORDER = (
    "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, "
    "l_returnflag, l_linestatus, l_shipdate"
)


def lineitem_rows() -> dict[str, str]:
    fixed = lambda c, k: f"floor({c} * {k} + 0.5)::BIGINT"
    return {
        "data": f"SELECT row_number() OVER (ORDER BY {LINEITEM_ORDER}) AS id, ["
        + ", ".join(
            [fixed("l_quantity", "20000.0"), fixed("l_extendedprice", "10.0"), fixed("l_discount", "10000000.0"), fixed("l_tax", "12500000.0")]
        )
        + "] AS vec FROM lineitem"
    }


def letter_rows() -> dict[str, str]:
    low = "lower(coalesce(text, ''))"
    counts = "[" + ", ".join(f"(length({low}) - length(replace({low}, '{c}', '')))" for c in LETTERS) + "]"
    return {
        "counts": f"SELECT doc_id AS id, {counts} AS c FROM documents",
        "data": "SELECT id, list_transform(c, lambda x: CASE WHEN list_sum(c) > 0 THEN floor(x * 1000000.0 / list_sum(c))::BIGINT ELSE 0 END) AS vec FROM counts",
    }


def minhash(tokens: str, perms: Permutations, i: int) -> str:
    return f"list_min(list_transform({tokens}, lambda x: {perms.sql('x', i)}))"


def kl_members(K: int, L: int, perms: Permutations, source: str = "sets") -> dict[str, str]:
    hs = ", ".join(f"{minhash('tokens', perms, i)} AS h{i}" for i in range(K * L))
    # an empty set has no minima: its signature is the empty text in every table
    sig = ", ".join(
        "{'l': %d, 's': concat_ws('_', %s)}" % (l, ", ".join(f"h{l * K + k}::VARCHAR" for k in range(K))) for l in range(L)
    )
    return {
        "hashed": f"SELECT id, {hs} FROM {source}",
        "exploded": f"SELECT id, unnest([{sig}]) AS s FROM hashed",
        "members": "SELECT s.l::VARCHAR || ':' || s.s AS bucket_id, s.l::INTEGER AS table_id, id FROM exploded",
    }


def dot(vec: str, direction: list[int]) -> str:
    return " + ".join(f"{vec}[{i + 1}] * ({d})" for i, d in enumerate(direction))


def projected(directions: list[list[int]], vec: str = "vec") -> dict[str, str]:
    """Integer dot products by an unnested direction table, to keep the text short."""
    dirs = " UNION ALL ".join(f"SELECT {i} AS table_id, {d} AS d" for i, d in enumerate(directions))
    return {
        "dirs": dirs,
        "proj": f"SELECT table_id, id, list_sum(list_transform(range(1, len(d) + 1), lambda i: {vec}[i]::BIGINT * d[i]::BIGINT))::BIGINT AS h FROM data, dirs",
    }


def dense_members(directions: list[list[int]], t: int) -> dict[str, str]:
    return projected(directions) | {
        "members": f"SELECT table_id::VARCHAR || ':' || (ntile({t}) OVER (PARTITION BY table_id ORDER BY h, id) - 1)::VARCHAR AS bucket_id, table_id::INTEGER AS table_id, id FROM proj"
    }


def doph_coords(D: int, seed: int, source: str = "sets") -> dict[str, str]:
    perm, width = affine_perms(1, seed), width_of(D)
    return {
        "least": f"SELECT id, v // {width} AS r, min(v) AS v FROM (SELECT id, {perm.sql('t', 0)} AS v FROM (SELECT id, unnest(tokens) AS t FROM {source})) GROUP BY id, v // {width}",
        "grid": f"SELECT id, unnest(range(0, {D})) AS r FROM (SELECT DISTINCT id FROM {source})",
        "filled": "SELECT g.id, g.r, l.v, first_value(l.v IGNORE NULLS) OVER (PARTITION BY g.id ORDER BY g.r ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS nxt, first_value(l.v IGNORE NULLS) OVER (PARTITION BY g.id ORDER BY g.r ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS fst FROM grid g LEFT JOIN least l ON l.id = g.id AND l.r = g.r",
        "coords": "SELECT id, list(coalesce(nxt, fst, -1) ORDER BY r) AS coords FROM filled GROUP BY id",
    }


COORD_SETS = {
    "csets": "SELECT id, list_transform(coords, lambda v, i: (v * 521 + (i - 1) * 7919) % 268435399) AS tokens FROM coords"
}


def seeding(K: int, L: int, delta: int, perms: Permutations, source: str = "members", out: str = "groups", least: int = 2, parts: int | None = None, prune: bool = True, p: str = "") -> dict[str, str]:
    """Signatures, bins, vote and threshold over ``source``(bucket_id, id[, table_id])."""
    hs = ", ".join(f"min({perms.sql('id', i)}) AS h{i}" for i in range(K * L))
    rows = source
    ctes: dict[str, str] = {}
    key = ""
    part = ""
    if parts:
        rows = f"{p}parted"
        ctes[rows] = f"SELECT (table_id % {parts})::VARCHAR || '/' || bucket_id AS bucket_id, (table_id % {parts})::VARCHAR AS part, id FROM {source}"
        key, part = "part || ':' || ", ", part"
    sig = ", ".join("{'l': %d, 's': %s}" % (l, " || '_' || ".join(f"h{l * K + k}::VARCHAR" for k in range(K))) for l in range(L))
    bound = f" AND sum(size) >= {delta} * (count(*) // 2 + 1)" if prune else ""
    ctes |= {
        f"{p}sigs": f"SELECT bucket_id{part}, count(*) AS size, {hs} FROM {rows} GROUP BY bucket_id{part}",
        f"{p}placed": f"SELECT bucket_id, size, s.l::INTEGER AS bin_table, {key}s.l::VARCHAR || ':' || s.s AS bin_id FROM (SELECT bucket_id, size{part}, unnest([{sig}]) AS s FROM {p}sigs)",
        f"{p}totals": f"SELECT bin_id, count(*) AS bin_size FROM {p}placed GROUP BY bin_id HAVING count(*) >= {least}{bound}",
        f"{p}bins": f"SELECT bin_id, bin_table, bucket_id, bin_size FROM {p}placed JOIN {p}totals USING (bin_id)",
        f"{p}voted": f"SELECT b.bin_id AS group_id, m.id, count(*) AS votes, b.bin_size FROM {p}bins b JOIN {rows} m ON m.bucket_id = b.bucket_id GROUP BY b.bin_id, b.bin_size, m.id HAVING count(*) * 2 > b.bin_size",
        out: f"SELECT * FROM {p}voted WHERE group_id IN (SELECT group_id FROM {p}voted GROUP BY group_id HAVING count(*) >= {delta})",
    }
    return ctes


def dedup(K: int, perms: Permutations, source: str = "groups", out: str = "seeds", singletons: str = "keep") -> dict[str, str]:
    return {"as_buckets": f"SELECT group_id AS bucket_id, id FROM {source}"} | seeding(
        K, 1, 1, perms, "as_buckets", out, 1 if singletons == "keep" else 2, prune=False, p="d_"
    )


NUMBERED = {
    "ids": "SELECT group_id, row_number() OVER (ORDER BY group_id) AS seed_id FROM (SELECT DISTINCT group_id FROM seeds)",
    "numbered": "SELECT s.id, i.seed_id FROM seeds s JOIN ids i USING (group_id)",
}


def centroids(groups: str = "numbered", out: str = "centers") -> dict[str, str]:
    return {
        f"{out}_d": f"SELECT seed_id, i, sum(v) AS s, count(*) AS n FROM (SELECT g.seed_id, unnest(range(1, len(d.vec) + 1)) AS i, unnest(d.vec) AS v FROM {groups} g JOIN data d USING (id)) GROUP BY seed_id, i",
        out: f"SELECT seed_id, list(floor((2 * s + n) / (2.0 * n))::BIGINT ORDER BY i) AS vec, max(n) AS size FROM {out}_d GROUP BY seed_id",
    }


def modes(groups: str = "numbered", source: str = "csets", out: str = "centers") -> dict[str, str]:
    return {
        f"{out}_n": f"SELECT seed_id, pos, value, count(*) AS n FROM (SELECT g.seed_id, unnest(range(0, len(d.tokens))) AS pos, unnest(d.tokens) AS value FROM {groups} g JOIN {source} d USING (id)) GROUP BY ALL",
        f"{out}_b": f"SELECT seed_id, pos, value FROM {out}_n QUALIFY row_number() OVER (PARTITION BY seed_id, pos ORDER BY n DESC, value) = 1",
        out: f"SELECT b.seed_id, list(value ORDER BY pos) AS modes, any_value(z.size) AS size FROM {out}_b b JOIN (SELECT seed_id, count(*) AS size FROM {groups} JOIN {source} USING (id) GROUP BY seed_id) z USING (seed_id) GROUP BY b.seed_id",
    }


def assign_dense(out: str = "assigned", centers: str = "centers") -> dict[str, str]:
    d = "sqrt(list_sum(list_transform(range(1, len(d.vec) + 1), lambda i: ((d.vec[i] - c.vec[i]) * (d.vec[i] - c.vec[i]))::DOUBLE)))"
    return {
        f"{out}_all": f"SELECT d.id, c.seed_id, {d} AS dist FROM data d, {centers} c",
        out: f"SELECT id, seed_id AS cluster_id, dist FROM {out}_all QUALIFY row_number() OVER (PARTITION BY id ORDER BY dist, seed_id) = 1",
    }


def assign_match(out: str = "assigned", source: str = "csets", centers: str = "centers") -> dict[str, str]:
    m = "list_sum(list_transform(range(1, len(d.tokens) + 1), lambda i: (d.tokens[i] = c.modes[i])::INTEGER))"
    return {
        f"{out}_all": f"SELECT d.id, c.seed_id, {m} AS m, len(d.tokens) AS n FROM {source} d, {centers} c",
        out: f"SELECT id, seed_id AS cluster_id, (1 - m / (2.0 * n - m))::DOUBLE AS dist FROM {out}_all QUALIFY row_number() OVER (PARTITION BY id ORDER BY m DESC, seed_id) = 1",
    }


RADIUS = (
    "SELECT count(*)::BIGINT AS k_star, sum(size)::BIGINT AS n, round(avg(radius), 6) AS mean_radius, "
    "round(max(radius), 6) AS max_radius, round(sum(radius * size) / sum(size), 6) AS weighted_radius "
    "FROM (SELECT cluster_id, count(*) AS size, max(dist) AS radius FROM assigned GROUP BY cluster_id)"
)
