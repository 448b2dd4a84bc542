"""URL filters: a path-template tree per host, judged by smoothed labelled purity.

Rules label the urls they fit. For each host, paths become templates level by level: digits and
long hexadecimal runs are wildcards from the start; children too many and too rare become ``*``;
siblings with the same children become one branch unless their labelled urls differ beyond chance.
A template is rejected if its labelled urls, smoothed level by level towards those of the branch
above, are blocked often enough; a template without labels has its nearest labelled ancestor's
purity. A url that no rule fits gets its template's verdict, and is allowed on hosts without labels.

Equal (host, path) pairs are counted before anything moves, so a hot host is as many rows as it
has templates. Defined results: null urls and urls without ``://`` have an empty host and path, no
rule, and are allowed; segments beyond ``DEPTH`` are one; repeated rows give a row each and count
each; a purity exactly at the limit rejects; of rules as long as each other the later text wins;
other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.columns import ascii_lower
from bucketseed.staging import counted

#: (host, path, verdict), in natural order.
RULES = (
    ("net", "/", "block"),
    ("example.net", "/en/", "allow"),
    ("example.com", "/de/", "block"),
    ("org", "/fr/", "allow"),
)
#: The tree ends with the longest path, or here.
DEPTH = 16
OUTCOMES = ("block", "allow", "free")


def parsed(pages: DataFrame, url: str = "url") -> DataFrame:
    """(page_id, host, path) of every row."""
    u = F.coalesce(F.col(url), F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, u.substr(at + 3, F.length(u))).otherwise("")
    return pages.select(
        "page_id",
        ascii_lower(F.regexp_extract(rest, r"^[^/?#]*", 0)).alias("host"),
        F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1).alias("path"),
    )


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, as struct(rule, verdict); null without one."""
    fitting = [
        F.when(
            ((host == h) | host.endswith("." + h)) & path.startswith(p),
            F.struct(F.lit(len(h + p)).alias("n"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict")),
        )
        for h, p, v in rules
    ]
    return F.array_max(F.filter(F.array(*fitting), lambda r: r.isNotNull()))


def typed_segments(path: Column, depth: int) -> Column:
    """The segments with their variable parts as wildcards; those beyond ``depth`` are one."""
    segments = F.slice(F.split(path, "/"), 2, 1_000_000)
    shaped = F.transform(
        segments,
        lambda s: F.regexp_replace(
            F.regexp_replace(s, r"(?i)^(?=.*[0-9])[0-9a-f-]{16,}$", "<hex>"), r"[0-9]+", "<n>"
        ),
    )
    return F.concat(
        F.slice(shaped, 1, depth),
        F.when(F.size(shaped) > depth, F.array(F.lit("<rest>"))).otherwise(F.array().cast("array<string>")),
    )


def template_tree(
    paths: DataFrame,
    depth: int = DEPTH,
    max_children: int = 50,
    min_share: float = 0.01,
    critical: float = 6.63,
    weight: float = 5.0,
    prior: float = 0.5,
) -> DataFrame:
    """Adds template, purity and support to counts (host, typed, block, allow, free).

    Level by level, rare children among too many become ``*``. Siblings with the same children
    become ``*`` too, if the blocked and allowed urls of each don't differ beyond chance
    (``critical``, chi-squared) from theirs together; a sibling without labels differs from nothing.
    purity: a node's blocked share of its labelled urls, smoothed by ``weight`` towards its parent's,
    the host's towards ``prior``. support: labelled urls of the last node above that has any.
    """
    blocked, allowed = F.col("block"), F.col("allow")

    def judged(rows: DataFrame, over: list[str], live: Column) -> DataFrame:
        """The node's counts enter purity and support of the rows that reach this level."""
        nodes = rows.filter(live).groupBy(*over).agg(F.sum("block").alias("_nb"), F.sum("allow").alias("_na"))
        nodes = nodes.select(*[F.col(c).alias(f"_{c}") for c in over], "_nb", "_na")
        same = live
        for c in over:
            same = same & (F.col(c) == F.col(f"_{c}"))
        known = F.col("_nb") + F.col("_na")
        return rows.join(nodes, same, "left").select(
            *[c for c in rows.columns if c not in ("purity", "support")],
            F.when(known > 0, (F.col("_nb") + weight * F.col("purity")) / (known + weight)).otherwise(F.col("purity")).alias("purity"),
            F.when(known > 0, known).otherwise(F.col("support")).alias("support"),
        )

    start = paths.withColumns(
        {"template": F.array().cast("array<string>"), "purity": F.lit(float(prior)), "support": F.lit(0).cast("bigint")}
    )
    tree, _ = counted(judged(start, ["host"], F.lit(True)), "tree")
    for level in range(depth + 1):
        child, below = F.get("typed", F.lit(level)), F.get("typed", F.lit(level + 1))
        kids, n = counted(
            tree.filter(child.isNotNull())
            .groupBy("host", "template", child.alias("kid"), F.coalesce(below, F.lit("")).alias("below"))
            .agg(*[F.sum(o).alias(o) for o in OUTCOMES])
            .groupBy("host", "template", "kid")
            .agg(
                *[F.sum(o).alias(o) for o in OUTCOMES],
                # the set of the children's names: their number and hash
                F.struct(F.count("*").alias("k"), F.bit_xor(F.xxhash64("below")).alias("h")).alias("shape"),
            )
            .withColumn("n", sum(F.col(o) for o in OUTCOMES)),
            "kids",
        )
        if not n:
            break
        parents = kids.groupBy("host", "template").agg(F.count("*").alias("k"), F.sum("n").alias("pn"))
        pools = kids.groupBy("host", "template", "shape").agg(
            F.count("*").alias("same"), F.sum("block").alias("pb"), F.sum("allow").alias("pa")
        )
        share = F.col("pb") / (F.col("pb") + F.col("pa"))
        known = blocked + allowed
        differs = F.when(
            (known > 0) & (F.col("pb") > 0) & (F.col("pa") > 0),
            F.pow(blocked - known * share, F.lit(2.0)) / (known * share * (1 - share)),
        ).otherwise(0.0)
        named = (
            kids.join(parents, ["host", "template"])
            .join(pools, ["host", "template", "shape"])
            .select(
                F.col("host").alias("_host"),
                F.col("template").alias("_above"),
                F.col("kid").alias("_kid"),
                F.when((F.col("k") > max_children) & (F.col("n") < min_share * F.col("pn")), F.lit("*"))
                .when((F.col("same") > 1) & (differs <= critical), F.concat(F.lit("*"), F.col("shape.h").cast("string")))
                .otherwise(F.col("kid"))
                .alias("_name"),
            )
        )
        deeper, _ = counted(
            tree.join(
                named,
                (F.col("host") == F.col("_host")) & (F.col("template") == F.col("_above")) & (child == F.col("_kid")),
                "left",
            ).select(
                *paths.columns,
                "purity",
                "support",
                F.when(F.col("_name").isNull(), F.col("template"))
                .otherwise(F.concat("template", F.array("_name")))
                .alias("template"),
            ),
            "named",
        )
        tree, _ = counted(judged(deeper, ["host", "template"], F.size("template") > level), "tree")
    return tree


def judge_urls(
    pages: DataFrame,
    rules=RULES,
    url: str = "url",
    depth: int = DEPTH,
    least: float = 0.8,
    min_labelled: int = 5,
    **options,
) -> DataFrame:
    """(page_id, host, path, rule, verdict, purity) of every row; purity is null where a rule fits."""
    rows = (
        parsed(pages, url)
        .withColumn("_rule", rule_of(F.col("host"), F.col("path"), rules))
        .withColumn("_typed", typed_segments(F.col("path"), depth))
    )
    verdict = F.coalesce("_rule.verdict", F.lit("free"))
    paths, _ = counted(
        rows.filter("host <> ''")
        .groupBy("host", F.col("_typed").alias("typed"))
        .agg(*[F.sum((verdict == o).cast("bigint")).alias(o) for o in OUTCOMES]),
        "paths",
    )
    judged = (
        template_tree(paths, depth, **options)
        .filter("free > 0")
        .select(
            F.col("host").alias("_h"),
            F.col("typed").alias("_t"),
            "purity",
            ((F.col("purity") >= least) & (F.col("support") >= min_labelled)).alias("_rejected"),
        )
    )
    return rows.join(
        judged, F.col("_rule").isNull() & (F.col("host") == F.col("_h")) & (F.col("_typed") == F.col("_t")), "left"
    ).select(
        "page_id",
        "host",
        "path",
        "_rule.rule",
        F.coalesce("_rule.verdict", F.when(F.col("_rejected"), "block").otherwise("allow")).alias("verdict"),
        "purity",
    )


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    return judge_urls(load(spark, sf_dir, "pages")).drop("purity")
