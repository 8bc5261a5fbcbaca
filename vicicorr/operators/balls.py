"""Vicinities: breadth-first balls about a set of seeds or about each of many roots."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import shared_dir


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the cluster's shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def set_ball(adj: DataFrame, seeds: DataFrame, h: int, cut_from: int = 3) -> DataFrame:
    """(node, dist): all nodes within ``h`` hops of any seed, each adjacency list read once.

    One search serves all seeds; only newly met nodes go on.  Hops from
    ``cut_from`` on are checkpointed so that the plan stays short."""
    seen = seeds.select("node").distinct().withColumn("dist", F.lit(0))
    frontier = seen
    for d in range(1, h + 1):
        met = frontier.join(adj, frontier.node == adj.u).select(F.col("v").alias("node")).distinct()
        frontier = met.join(seen.select("node"), "node", "left_anti").withColumn("dist", F.lit(d))
        seen = seen.unionByName(frontier)
        if d >= cut_from:
            seen = cut(seen)
            frontier = seen.where(F.col("dist") == d)
    return seen


def balls(adj: DataFrame, roots: DataFrame, h: int, cut_from: int = 3) -> DataFrame:
    """(root, node, dist): the ``h``-ball of every root, root included."""
    seen = roots.select(F.col("root"), F.col("root").alias("node")).distinct().withColumn("dist", F.lit(0))
    frontier = seen
    for d in range(1, h + 1):
        met = frontier.join(adj, frontier.node == adj.u).select("root", F.col("v").alias("node")).distinct()
        frontier = met.join(seen.select("root", "node"), ["root", "node"], "left_anti").withColumn("dist", F.lit(d))
        seen = seen.unionByName(frontier)
        if d >= cut_from:
            seen = cut(seen)
            frontier = seen.where(F.col("dist") == d)
    return seen


def weighted_balls(arcs: DataFrame, roots: DataFrame, max_dist: float, rounds: int) -> DataFrame:
    """arcs(u, v, w): (root, node, dist) with the least path length up to ``max_dist`` over at most ``rounds`` arcs; directed arcs as given."""
    seen = roots.select("root", F.col("root").alias("node"), F.lit(0.0).alias("dist"))
    for d in range(rounds):
        step = seen.join(arcs, seen.node == arcs.u).select("root", F.col("v").alias("node"), (F.col("dist") + F.col("w")).alias("dist")).where(F.col("dist") <= max_dist)
        seen = seen.unionByName(step).groupBy("root", "node").agg(F.min("dist").alias("dist"))
        if d >= 2:
            seen = cut(seen)
    return seen


def mask_balls(adj: DataFrame, roots: DataFrame, h: int, cut_from: int = 2) -> DataFrame:
    """(block, node, mask): bit i of ``mask`` says that root number i of the block reaches the node.

    Sixty-two roots travel in one BIGINT, so a hop is one ``bit_or`` aggregate with
    a row for each (block, node) instead of each (root, node).  roots(root, number)
    numbers the roots from 0."""
    masks = roots.select(F.expr("number div 62").alias("block"), F.col("root").alias("node"), F.expr("shiftleft(1L, int(number % 62))").alias("mask")).groupBy("block", "node").agg(F.bit_or("mask").alias("mask"))
    for d in range(h):
        step = masks.join(adj, masks.node == adj.u).select("block", F.col("v").alias("node"), "mask")
        masks = masks.unionByName(step).groupBy("block", "node").agg(F.bit_or("mask").alias("mask"))
        if d + 1 >= cut_from:
            masks = cut(masks)
    return masks


def numbered_roots(roots: DataFrame, block: int = 992) -> DataFrame:
    """roots(root) -> (root, number), numbered from 0 within hash buckets of about ``block`` roots, so that no task sorts them all.

    A bucket's numbers start at a multiple of 2**20 x 62, far above its size."""
    roots = cut(roots.select("root").distinct())
    buckets = max(1, -(-roots.count() // block))
    at = F.pmod(F.xxhash64("root"), F.lit(buckets))
    own = F.row_number().over(Window.partitionBy("bucket").orderBy("root")) - 1
    return roots.withColumn("bucket", at).select("root", (F.col("bucket") * F.lit(62 << 20) + own).cast("long").alias("number"))


def mask_counts(adj: DataFrame, roots: DataFrame, flags: DataFrame, h: int) -> DataFrame:
    """(root, size, <nodes met with each flag>, c): ball sizes and flagged nodes of every root.

    flags(node, f1, f2, ...) are booleans; ``c`` counts the flagged nodes met.  Set
    bits are spread only within a task, on their way into its partial counts, so no row for
    a (root, node) is ever shuffled or stored."""
    numbers = numbered_roots(roots)
    names = [c for c in flags.columns if c != "node"]
    masks = mask_balls(adj, numbers, h, cut_from=max(h, 2)).join(flags, "node", "left")
    place = F.explode(F.expr("filter(sequence(0, 61), i -> (shiftright(mask, i) & 1) = 1)"))
    rows = masks.select("block", *names, place.alias("place"))
    counts = rows.groupBy("block", "place").agg(F.count(F.lit(1)).alias("size"), *(F.count_if(x).alias(x) for x in names), F.count(names[0]).alias("c"))
    return counts.withColumn("number", F.col("block") * 62 + F.col("place")).join(numbers, "number").select("root", "size", *names, "c")


def hits_within(adj: DataFrame, roots: DataFrame, event: DataFrame, h: int) -> DataFrame:
    """(node): roots(node) that see a node of event(node) within ``h`` hops; a root goes no further after its first hit."""
    front = roots.select(F.col("node").alias("root"), "node").distinct()
    event = event.select("node").distinct()
    found, open_ = None, front
    for d in range(h + 1):
        hit = open_.join(event, "node", "left_semi").select("root").distinct()
        found = hit if found is None else found.union(hit)
        if d < h:
            open_ = open_.join(hit, "root", "left_anti").join(adj, F.col("node") == F.col("u")).select("root", F.col("v").alias("node")).distinct()
            if d >= 1:
                open_, found = cut(open_), cut(found)
    return found.select(F.col("root").alias("node")).distinct()


def induced_edges(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends among ``nodes``."""
    return edges.join(nodes.select(F.col("node").alias("src")), "src", "left_semi").join(nodes.select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst")
