"""Balls of many roots counted on a skeleton of the graph.

Trees that hang on the rest of the graph are counted along their edges, and nodes
with equal neighbours (twins) are searched as one.  Both are exact: a hanging tree
is met through one edge only, and twins are equally far from every other node, two
hops from one another.  What is left, the core between classes of twins, is searched by blocks (two hops) or masks.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import EventGraph
from .balls import cut, mask_counts, numbered_roots
from .blocks import COUNTS, two_hop_counts

#: Rounds of stripping leaves, each only while a 50th of the nodes left are leaves; likewise twins are merged if a 50th of the nodes have one.
ROUNDS, SHARE = 6, 50


@dataclass(frozen=True)
class Skeleton:
    hung: DataFrame | None  # (node, parent, level): parents are of a higher level or in the core
    levels: int
    twins: DataFrame | None  # (node, rep): core nodes with the neighbours of a smaller one
    arcs: DataFrame  # (u, v) between classes of core nodes
    kept: dict = field(default_factory=dict, compare=False)  # the arcs as packed for two hops


def _strip(arcs: DataFrame) -> tuple[DataFrame | None, int, DataFrame]:
    hung, level = None, 0
    for r in range(1, ROUNDS + 1):
        deg = arcs.groupBy(F.col("u").alias("node")).agg(F.count(F.lit(1)).alias("deg"), F.max("v").alias("parent"))
        n, leaves = deg.agg(F.count(F.lit(1)), F.count_if(F.col("deg") == 1)).first()
        if not leaves or leaves * SHARE < n:
            break
        leaf = deg.where("deg = 1").select("node", "parent")
        ends = leaf.where("node > parent").select(F.col("parent").alias("node"), F.col("node").alias("parent"))
        gone = cut(leaf.join(ends, ["node", "parent"], "left_anti").withColumn("level", F.lit(r)))  # of two leaves at one edge the smaller stays
        arcs = cut(arcs.join(gone.select(F.col("node").alias("u")), "u", "left_anti").join(gone.select(F.col("node").alias("v")), "v", "left_anti").select("u", "v"))
        hung, level = gone if hung is None else hung.union(gone), r
    return hung, level, arcs


def _merge_twins(arcs: DataFrame) -> tuple[DataFrame | None, DataFrame]:
    keys = ["deg", "x", "y"]
    sign = arcs.groupBy(F.col("u").alias("node")).agg(F.count(F.lit(1)).alias("deg"), F.bit_xor(F.xxhash64("v")).alias("x"), F.bit_xor(F.xxhash64("v", F.lit(1))).alias("y"))
    groups = sign.groupBy(*keys).agg(F.min("node").alias("rep"), F.count(F.lit(1)).alias("n"))
    n, more = groups.agg(F.sum("n"), F.sum(F.col("n") - 1)).first()
    if not more or more * SHARE < n:
        return None, arcs
    alike = cut(sign.join(groups.where("n > 1"), keys).where("node <> rep").select("node", "rep", "deg"))
    # hashes only propose: a twin has each neighbour of its representative
    shared = arcs.join(alike, F.col("u") == F.col("node")).select("node", "rep", "deg", "v").join(arcs.select(F.col("u").alias("rep"), "v"), ["rep", "v"], "left_semi")
    twins = cut(shared.groupBy("node", "rep", "deg").agg(F.count(F.lit(1)).alias("n")).where("n = deg").select("node", "rep"))
    some = arcs.join(twins.select(F.col("node").alias("u")), "u", "left_anti").join(twins.select(F.col("node").alias("v"), "rep"), "v", "left")
    return twins, cut(some.select("u", F.coalesce("rep", "v").alias("v")).distinct())


def skeleton(g: EventGraph) -> Skeleton:
    """The graph's skeleton, found once; events play no part in it."""
    if "skeleton" not in g.kept:
        hung, levels, arcs = _strip(g.adj)
        twins, arcs = _merge_twins(arcs)
        g.kept["skeleton"] = Skeleton(hung, levels, twins, arcs)
    return g.kept["skeleton"]


def _sum(rows: DataFrame, *by: str) -> DataFrame:
    return rows.groupBy(*by).agg(*(F.sum(x).alias(x) for x in COUNTS))


def _own(nodes: DataFrame, flags: DataFrame) -> DataFrame:
    """(node, <counts>): what a node itself adds."""
    one = lambda x: F.coalesce(F.col(x).cast("long"), F.lit(0).cast("long")).alias(x)
    return nodes.join(flags.withColumn("c", F.lit(1)), "node", "left").select("node", F.lit(1).cast("long").alias("size"), one("cnt_a"), one("cnt_b"), one("c"))


def _below(sk: Skeleton, flags: DataFrame, h: int) -> DataFrame | None:
    """(node, k, <counts>): what hangs below a node at exactly k >= 1 hops."""
    got = None
    for r in range(1, sk.levels + 1):
        at = sk.hung.where(F.col("level") == r).select("node", "parent")
        up = _own(at.select("node"), flags).join(at, "node").select(F.col("parent").alias("node"), F.lit(1).alias("k"), *COUNTS)
        if got is not None:
            up = up.union(got.where(F.col("k") < h).join(at, "node").select(F.col("parent").alias("node"), F.col("k") + 1, *COUNTS))
        up = cut(_sum(up, "node", "k"))
        got = up if got is None else got.union(up)
    return None if got is None else cut(_sum(got, "node", "k"))


def _core_balls(sk: Skeleton, roots: DataFrame, weights: DataFrame, h: int, every: bool) -> DataFrame:
    """(rep, t, <counts>): what a class meets within t hops, its own members included; for all t up to h or h alone.

    weights(rep, k, <counts>) hang k hops below a class; a ball of t hops holds those k below any class within t - k."""
    if h == 2:
        roots = roots.select("root").distinct()
        met = two_hop_counts(sk.arcs, roots, weights.where("k = 0").withColumnRenamed("rep", "node"), sk.kept).select(F.col("root").alias("rep"), F.lit(2).alias("t"), *COUNTS)
        if every:  # what hangs below the class and its neighbours
            itself = roots.select(F.col("root").alias("rep"), F.col("root").alias("node"))
            near = itself.union(itself.join(sk.arcs, F.col("node") == F.col("u")).select("rep", "v"))
            below = weights.withColumnRenamed("rep", "node")
            met = met.union(itself.join(below.where(F.col("k") <= 2), "node").select("rep", F.col("k").alias("t"), *COUNTS)).union(near.join(below.where(F.col("k") <= 1), "node").select("rep", F.col("k") + 1, *COUNTS))
        return _sum(met, "rep", "t")
    numbers = numbered_roots(roots)
    masks = numbers.select(F.expr("number div 62").alias("block"), F.col("root").alias("rep"), F.expr("shiftleft(1L, int(number % 62))").alias("mask")).groupBy("block", "rep").agg(F.bit_or("mask").alias("mask"))
    seen = [masks]
    for d in range(h):
        step = masks.join(sk.arcs, masks.rep == sk.arcs.u).select("block", F.col("v").alias("rep"), "mask")
        masks = masks.unionByName(step).groupBy("block", "rep").agg(F.bit_or("mask").alias("mask"))
        if d:
            masks = cut(masks)
        seen.append(masks)
    place = F.explode(F.expr("filter(sequence(0, 61), i -> (shiftright(mask, i) & 1) = 1)"))
    met = None
    for j in range(h + 1) if every else [h]:
        part = seen[j].join(weights.where(F.col("k") <= h - j), "rep").select("block", (F.col("k") + j).alias("t"), *COUNTS, place.alias("place"))
        part = _sum(part, "block", "place", "t")
        met = part if met is None else met.union(part)
    met = met.withColumn("number", F.col("block") * 62 + F.col("place")).join(numbers, "number")
    return _sum(met.select(F.col("root").alias("rep"), "t", *COUNTS), "rep", "t")


def ball_counts(g: EventGraph, roots: DataFrame, flags: DataFrame, h: int) -> DataFrame:
    """(root, size, cnt_a, cnt_b, c): as ``mask_counts``, on the skeleton; flags(node, cnt_a, cnt_b) are booleans.  From two hops on."""
    sk = skeleton(g)
    plain = sk.hung is None and sk.twins is None
    if plain and h > 2:
        return mask_counts(g.adj, roots, flags, h)
    roots = roots.select(F.col("root").alias("node")).distinct()
    nodes = g.nodes.select(F.col("id").alias("node")).union(roots).distinct()
    if plain:
        return two_hop_counts(g.adj, roots.toDF("root"), _own(nodes, flags), sk.kept)
    below = _below(sk, flags, h)
    leaves = None
    need, core = roots, nodes
    if sk.hung is not None:
        leaves = roots.join(sk.hung.where("level = 1").select("node", "parent"), "node")
        need = cut(roots.join(leaves.select("node"), "node", "left_anti").union(leaves.select("parent")).distinct())
        for r in range(2, sk.levels + 1):
            need = cut(need.union(need.join(sk.hung.where(F.col("level") == r), "node").select("parent")).distinct())
        core = nodes.join(sk.hung.select("node"), "node", "left_anti")
    own = _own(core, flags).select("node", F.lit(0).alias("k"), *COUNTS)
    if below is not None:
        own = own.union(below.join(sk.hung.select("node"), "node", "left_anti"))
    wanted = need if sk.hung is None else need.join(sk.hung.select("node"), "node", "left_anti")
    if sk.twins is None:
        found = _core_balls(sk, wanted.toDF("root"), own.withColumnRenamed("node", "rep"), h, True).withColumnRenamed("rep", "node")
    else:
        classed = lambda df: df.join(sk.twins, "node", "left").withColumn("rep", F.coalesce("rep", "node"))
        own = cut(classed(own))
        total = cut(_sum(own, "rep", "k"))
        wanted = cut(classed(wanted))
        quotient = _core_balls(sk, wanted.select(F.col("rep").alias("root")), total, h, sk.hung is not None)
        # within one hop a node meets itself, not its twins
        reps = sk.twins.select("rep").distinct()
        mixed = wanted.join(reps, "rep", "left_semi")
        hops = F.explode(F.array(F.col("k"), F.col("k") + 1)).alias("t")
        itself = own.join(mixed.select("node"), "node", "left_semi").select("node", hops, *COUNTS)
        others = total.join(mixed, "rep").select("node", hops, *((-F.col(x)).alias(x) for x in COUNTS))
        found = wanted.join(quotient, "rep").select("node", "t", *COUNTS).union(itself.union(others).where(F.col("t") <= h))
        found = _sum(found, "node", "t")
    found = cut(found)
    for r in range(sk.levels, 1, -1):
        # a hanging node sees what its parent sees a hop less far, and what is below itself at t and t - 1 hops, which the parent sees too late
        at = need.join(sk.hung.where(F.col("level") == r).select("node", "parent"), "node")
        seen = at.join(found.withColumnRenamed("node", "parent"), "parent").where(F.col("t") < h).select("node", (F.col("t") + 1).alias("t"), *COUNTS)
        mine = _own(at.select("node"), flags).select("node", F.lit(0).alias("k"), *COUNTS).union(below.join(at.select("node"), "node", "left_semi"))
        mine = mine.select("node", F.explode(F.array(F.col("k"), F.col("k") + 1)).alias("t"), *COUNTS).where(F.col("t") <= h)
        found = cut(found.union(_sum(seen.union(mine), "node", "t")))
    out = found.where(F.col("t") == h).join(roots, "node", "left_semi").select(F.col("node").alias("root"), *COUNTS)
    if leaves is not None:
        out = out.union(leaves.join(found.where(F.col("t") == h - 1).withColumnRenamed("node", "parent"), "parent").select("node", *COUNTS))
    return out
