"""Connected components of a link table, by least labels and pointer jumping over stage files."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.staging import counted


def components(links: DataFrame) -> DataFrame:
    """(node, comp) for every node of links (a, b); comp is the least node it reaches.

    Each round takes the least label among neighbours and then the label's own label, so long
    chains halve; only rows of linked nodes move, and nothing is gathered on the driver.
    """
    arcs = links.select(F.col("a").alias("u"), F.col("b").alias("v"))
    arcs, _ = counted(arcs.union(arcs.select("v", "u")).filter("u <> v").distinct(), "arcs")
    labels = arcs.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("least"))
    labels, _ = counted(labels.select("node", F.least("node", "least").alias("comp")), "labels")
    while True:
        near = (
            arcs.join(labels.select(F.col("node").alias("v"), "comp"), "v")
            .groupBy(F.col("u").alias("node"))
            .agg(F.min("comp").alias("near"))
        )
        hop = labels.join(near, "node").select("node", F.col("comp").alias("was"), F.least("comp", "near").alias("mid"))
        jump = labels.select(F.col("node").alias("mid"), F.col("comp").alias("far"))
        after, _ = counted(
            hop.join(jump, "mid", "left").select(
                "node", F.least("mid", F.coalesce("far", "mid")).alias("comp"), "was"
            ),
            "labels",
        )
        labels = after.select("node", "comp")
        if after.filter(F.col("comp") != F.col("was")).isEmpty():
            return labels
