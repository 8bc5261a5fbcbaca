"""Screening of all event pairs on one shared sample."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import EventGraph
from .balls import balls
from .kendall import kendall_test
from .samplers import key


def shared_counts(g: EventGraph, n: int, h: int, events: list[str] | None = None, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """One sample of all nodes serves every pair: (node, size) and sparse (node, event, cnt)."""
    roots = g.nodes.orderBy(key(F.col("id"), seed=seed)).limit(n).select(F.col("id").alias("root"))
    reach = balls(g.adj, roots, h)
    occ = g.occ if events is None else g.occ.where(F.col("event").isin(events))
    sizes = reach.groupBy(F.col("root").alias("node")).agg(F.count(F.lit(1)).alias("size"))
    return sizes, reach.join(occ, "node").groupBy(F.col("root").alias("node"), "event").agg(F.count(F.lit(1)).alias("cnt"))


def screen(g: EventGraph, n: int, h: int, events: list[str] | None = None, least: int = 30, seed: int = 42) -> DataFrame:
    """(a, b, n, s, t, var_s, z, ...) for each pair of events that at least ``least`` sampled nodes see.

    In-sight nodes of a pair are those with a non-zero count of either event: they
    are a uniform sample of the pair's own population."""
    sizes, cnt = shared_counts(g, n, h, events, seed)
    names = cnt.select("event").distinct()
    pairs = names.toDF("a").join(names.toDF("b"), F.col("a") < F.col("b"))
    x = cnt.join(pairs, cnt.event == pairs.a).select("a", "b", "node", F.col("cnt").alias("cnt_a"), F.lit(0).alias("cnt_b"))
    y = cnt.join(pairs, cnt.event == pairs.b).select("a", "b", "node", F.lit(0).alias("cnt_a"), F.col("cnt").alias("cnt_b"))
    dens = x.union(y).groupBy("a", "b", "node").agg(F.sum("cnt_a").alias("cnt_a"), F.sum("cnt_b").alias("cnt_b")).join(sizes, "node")
    return kendall_test(dens, "a", "b").where(F.col("n") >= least)
