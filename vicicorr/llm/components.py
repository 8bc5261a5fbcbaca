"""Connected components by alternating star operations, with a checkpoint each round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed


def connected_components(links: DataFrame) -> DataFrame:
    """links(a, b) -> (node, label): the smallest node of each component, for every node that has a link.

    Two rounds of hanging nodes on the smallest neighbour alternate until
    nothing changes: O(log n) rounds, each an aggregate with map-side
    combination and a join that AQE can split.  Self links and repeats are
    harmless; null ends are dropped.
    """
    edges = checkpointed(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u IS NOT NULL AND v IS NOT NULL AND u <> v").distinct())

    def mark(e: DataFrame):
        r = e.agg(F.count(F.lit(1)), F.sum((F.xxhash64("u", "v") % 1_000_003))).first()
        return r[0], r[1]

    before = mark(edges)
    while before[0]:
        both = edges.union(edges.select("v", "u"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        # larger neighbours move to the smallest neighbour
        edges = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # smaller neighbours and the node itself move to the smallest
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        edges = edges.join(least, "u").select(F.col("v").alias("x"), "m").union(least.select("u", "m")).where("x <> m").select(F.col("x").alias("u"), F.col("m").alias("v")).distinct()
        edges = checkpointed(edges)
        after = mark(edges)
        if after == before:
            break
        before = after
    roots = edges.select(F.col("v").alias("node")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("label")).union(roots.select("node", F.col("node").alias("label"))).dropDuplicates(["node"])
