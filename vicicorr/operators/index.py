"""Index of vicinity sizes and what follows from it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import EventGraph
from .balls import balls, set_ball


def vicinity_sizes(g: EventGraph, h: int, nodes: DataFrame | None = None) -> DataFrame:
    """(node, h, size): exact ball sizes; one hop is the degree plus one."""
    roots = (g.nodes.select(F.col("id").alias("node")) if nodes is None else nodes).select("node")
    if h == 1:
        deg = g.adj.groupBy(F.col("u").alias("node")).agg(F.count(F.lit(1)).alias("deg"))
        return roots.join(deg, "node", "left").select("node", F.lit(1).alias("h"), (F.coalesce("deg", F.lit(0)) + 1).alias("size"))
    return balls(g.adj, roots.select(F.col("node").alias("root")), h).groupBy(F.col("root").alias("node")).agg(F.count(F.lit(1)).alias("size")).select("node", F.lit(h).alias("h"), "size")


def vicinity_edges(g: EventGraph, h: int, nodes: DataFrame | None = None) -> DataFrame:
    """(node, edges): edges within each ball."""
    roots = (g.nodes.select(F.col("id").alias("node")) if nodes is None else nodes).select(F.col("node").alias("root"))
    b = balls(g.adj, roots, h).select("root", "node")
    inside = b.join(g.edges, F.col("node") == F.col("src")).select("root", "dst").join(b.withColumnRenamed("node", "dst"), ["root", "dst"], "left_semi")
    n = inside.groupBy("root").agg(F.count(F.lit(1)).alias("edges"))
    return roots.join(n, "root", "left").select(F.col("root").alias("node"), F.coalesce("edges", F.lit(0)).alias("edges"))


def updated_sizes(old: DataFrame, g: EventGraph, changed: DataFrame, g_old: EventGraph, h: int) -> DataFrame:
    """Index after edges changed(src, dst): balls can only differ within h - 1 hops of a changed end, before or after."""
    ends = changed.select(F.col("src").alias("node")).union(changed.select("dst")).distinct()
    touched = set_ball(g.adj, ends, h - 1).select("node").union(set_ball(g_old.adj, ends, h - 1).select("node")).distinct()
    return old.join(touched, "node", "left_anti").unionByName(vicinity_sizes(g, h, touched))


def sketched_sizes(g: EventGraph, h: int) -> DataFrame:
    """(node, size): approximate sizes by merging sketches hop after hop, for planning only."""
    s = g.nodes.groupBy(F.col("id").alias("node")).agg(F.hll_sketch_agg("id").alias("s"))
    for _ in range(h):
        step = s.join(g.adj, F.col("node") == F.col("u")).select(F.col("v").alias("node"), "s")
        s = s.unionByName(step).groupBy("node").agg(F.hll_union_agg("s").alias("s"))
    return s.select("node", F.hll_sketch_estimate("s").alias("size"))
