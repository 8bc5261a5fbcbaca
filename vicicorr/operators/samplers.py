"""Ways to draw reference nodes.  Every choice is an md5 of ids and a seed: the same on retries, clusters and other engines."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import EventGraph
from .balls import balls, cut, hits_within
from .index import vicinity_sizes
from .kendall import densities, reference_population


def key(*cols, seed: int = 42) -> Column:
    return F.md5(F.concat_ws(":", *[c.cast("string") for c in cols], F.lit(str(seed))))


def number(*cols, seed: int = 42) -> Column:
    """60 bits of the key as a long."""
    return F.conv(F.substring(key(*cols, seed=seed), 1, 15), 16, 10).cast("long")


def naive_union(g: EventGraph, a: str, b: str, h: int) -> DataFrame:
    """A search from every event node and the union of all: the way to avoid."""
    return balls(g.adj, g.event_nodes(a, b).select(F.col("node").alias("root")), h).select("node").distinct()


def enumerate_sample(g: EventGraph, a: str, b: str, h: int, n: int, seed: int = 42) -> DataFrame:
    """Uniform sample of ``n`` from the population found by one search: (node, w = 1)."""
    return reference_population(g, a, b, h).select("node").orderBy(key(F.col("node"), seed=seed), "node").limit(n).withColumn("w", F.lit(1).cast("long"))


def stratified_sample(g: EventGraph, a: str, b: str, h: int, n: int, seed: int = 42) -> DataFrame:
    """As enumeration, but each distance from the events gives its share of ``n``, rounded up: (node, w = 1, dist)."""
    pop = cut(reference_population(g, a, b, h))
    shares = pop.groupBy("dist").agg(F.count(F.lit(1)).alias("u"))
    total = pop.agg(F.count(F.lit(1)).alias("all"))
    most = shares.crossJoin(total).select("dist", F.ceil(F.col("u") * n / F.col("all")).alias("most"))  # a row a distance
    within = F.row_number().over(Window.partitionBy("dist").orderBy(key(F.col("node"), seed=seed), "node"))
    return pop.withColumn("r", within).join(F.broadcast(most), "dist").where("r <= most").select("node", F.lit(1).cast("long").alias("w"), "dist")


def whole_graph_sample(g: EventGraph, a: str, b: str, h: int, n: int, seed: int = 42, first: int | None = None) -> DataFrame:
    """Nodes in random order, without replacement, until ``n`` see an event: (node, w, tried).

    Goes by ranges of the hash, so no slice is sorted: the next range is as wide as the
    hit rate so far calls for, twice the last at most.  ``tried`` is the number of
    nodes looked at up to the last one taken.  Ends when all nodes are used."""
    top = 1 << 60
    order = cut(g.nodes.select(F.col("id").alias("node"), key(F.col("id"), seed=seed).alias("k"), number(F.col("id"), seed=seed).alias("x")))
    total = order.count()
    event = g.event_nodes(a, b).select("node")
    low, width, hits, got = 0, top * min(1.0, (first or 2 * n) / max(total, 1)), None, 0
    while low < top and got < n:
        high = top if low + width >= top else int(low + width)
        some = order.where((F.col("x") >= low) & (F.col("x") < high))
        seen = some.join(hits_within(g.adj, some.select("node"), event, h), "node", "left_semi")
        hits = cut(seen if hits is None else hits.unionByName(seen))
        got, low = hits.count(), high
        width = min(2 * width, 1.2 * low * (n - got) / got + top / max(total, 1)) if got else 2 * width
    taken = hits.orderBy("k", "node").limit(n)
    last = taken.agg(F.max("k").alias("last"))
    tried = order.join(last, F.col("k") <= F.col("last")).agg(F.count(F.lit(1)).alias("tried"))
    return taken.select("node", F.lit(1).cast("long").alias("w")).crossJoin(tried)


def intervals(g: EventGraph, a: str, b: str, h: int, pieces: int = 256) -> DataFrame:
    """(node, size, lo): event nodes laid end to end by ball size, in id order.

    Prefix sums run within id ranges, whose totals (at most ``pieces``) are summed
    apart, so no task sorts all event nodes."""
    v = vicinity_sizes(g, h, g.event_nodes(a, b).select("node")).select("node", "size")
    lim = v.agg(F.min("node").alias("n0"), F.max("node").alias("n1"))
    v = v.crossJoin(lim).withColumn("r", F.floor((F.col("node") - F.col("n0")) * pieces / (F.col("n1") - F.col("n0") + 1)))
    before = Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1)
    base = v.groupBy("r").agg(F.sum("size").alias("total")).withColumn("base", F.coalesce(F.sum("total").over(before), F.lit(0))).select("r", "base")
    within = F.coalesce(F.sum("size").over(Window.partitionBy("r").orderBy("node").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return v.withColumn("in", within).join(base, "r").select("node", "size", (F.col("in") + F.col("base")).cast("long").alias("lo"))


def spread_draws(iv: DataFrame, first: int, last: int, seed: int = 42) -> DataFrame:
    """Draws number ``first`` to ``last`` over the checkpointed intervals: (j, root, size, at).

    A range join as an equi-join on bins of the average interval's width."""
    total, rows = iv.agg(F.sum("size"), F.count(F.lit(1))).first()
    spark = iv.sparkSession
    if not total:
        return spark.createDataFrame([], "j long, root long, size long, at long")
    width = max(1, total // rows)
    x = spark.range(first, last + 1).select(F.col("id").alias("j"), (number(F.col("id"), seed=seed) % total).alias("x")).withColumn("bin", F.floor(F.col("x") / width))
    bins = iv.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("lo") + F.col("size") - 1) / width))))
    return x.join(bins, "bin").where((F.col("x") >= F.col("lo")) & (F.col("x") < F.col("lo") + F.col("size"))).select("j", F.col("node").alias("root"), "size", (F.col("x") - F.col("lo")).alias("at"))


def weighted_draw(g: EventGraph, a: str, b: str, h: int, draws: int, seed: int = 42) -> DataFrame:
    """(j, root, size, at): the j-th draw takes event node ``root`` with chance in proportion to its ball, and place ``at`` in it."""
    return spread_draws(cut(intervals(g, a, b, h)), 1, draws, seed)


def members(g: EventGraph, drawn: DataFrame, h: int, k: int = 1, seed: int = 42, distinct_within: bool = False) -> DataFrame:
    """(j, i, node): the member of the drawn ball at its place and k - 1 more, drawn with replacement, or those next in hash order."""
    reach = balls(g.adj, drawn.select("root").distinct(), h).select("root", "node")
    reach = reach.withColumn("pos", F.row_number().over(Window.partitionBy("root").orderBy(key(F.col("node"), seed=seed), "node")) - 1)
    many = F.least(F.lit(k), F.col("size")).cast("int") if distinct_within else F.lit(k)
    picks = drawn.withColumn("i", F.explode(F.sequence(F.lit(1), many)))
    more = (F.col("at") + F.col("i") - 1) % F.col("size") if distinct_within else number(F.col("j"), F.col("i"), seed=seed) % F.col("size")
    picks = picks.withColumn("pos", F.when(F.col("i") == 1, F.col("at")).otherwise(more))
    return picks.join(reach, ["root", "pos"]).select("j", "i", "node")


def first_distinct(picks: DataFrame, n: int) -> DataFrame:
    """(node, w): draws in order up to the one that brings the n-th distinct node; w counts a node's draws."""
    place = F.struct("j", "i")
    firsts = picks.groupBy("node").agg(F.min(place).alias("f"))
    last = firsts.orderBy("f").limit(n).agg(F.max("f").alias("last"))
    return picks.crossJoin(F.broadcast(last)).where(place <= F.col("last")).groupBy("node").agg(F.count(F.lit(1)).alias("w"))


@dataclass(frozen=True)
class Draws:
    """What rounds of draws gave: refs(node, w), how many of the nodes asked for, whether the population ran out, and the draws made."""

    refs: DataFrame
    n_got: int
    exhausted: bool
    draws: int


def draw_rounds(g: EventGraph, a: str, b: str, h: int, n: int, k: int = 1, seed: int = 42, accept: bool = False, distinct_within: bool = False) -> Draws:
    """Rounds of draws, each twice the last, until ``n`` distinct nodes are there or all of the population.

    ``accept`` keeps a draw with chance 1 / c, c the event nodes that its node sees.  As
    draws are numbered and hashed, the first n distinct don't depend on the rounds.
    Once more draws than pairs (event node, member) have failed, one search counts the
    population, which then bounds what can be asked."""
    iv = cut(intervals(g, a, b, h))
    pairs = iv.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    if not pairs or n < 1:
        return Draws(g.nodes.sparkSession.createDataFrame([], "node long, w long"), 0, n > 0, 0)
    want, done, lot, kept, known = n, 0, max(64, -(-3 * n // (2 * k)) * (4 if accept else 1)), None, False
    while True:
        new = members(g, spread_draws(iv, done + 1, done + lot, seed), h, k, seed, distinct_within)
        if accept:
            new = cut(new)
            c = densities(g, new.select("node").distinct(), a, b, h).select("node", "c")
            new = new.join(c, "node").where(number(F.col("j"), F.lit("keep"), seed=seed) % F.col("c") == 0).select("j", "i", "node")
        kept = cut(new if kept is None else kept.unionByName(new))
        done += lot
        got = kept.select("node").distinct().count()
        if got >= want:
            break
        if done * k >= pairs and not known:
            known, want = True, min(n, reference_population(g, a, b, h).count())
            if got >= want:
                break
        lot *= 2
    last = kept.groupBy("node").agg(F.min("j").alias("j")).orderBy("j").limit(want).agg(F.max("j")).first()[0]
    return Draws(first_distinct(kept, want), min(got, want), want < n, last)


def importance_sample(g: EventGraph, a: str, b: str, h: int, n: int, k: int = 1, seed: int = 42, distinct_within: bool = False) -> DataFrame:
    """Draw pairs (event node, member) uniformly, ``k`` members a ball: (node, w) of the first ``n`` distinct nodes."""
    return draw_rounds(g, a, b, h, n, k, seed, distinct_within=distinct_within).refs


def rejection_sample(g: EventGraph, a: str, b: str, h: int, n: int, seed: int = 42) -> DataFrame:
    """As importance draws, each kept with chance 1 / c: (node, w = 1), the first ``n`` distinct; c counts the event nodes it sees."""
    return draw_rounds(g, a, b, h, n, seed=seed, accept=True).refs.select("node", F.lit(1).cast("long").alias("w"))


SAMPLERS = {"enumerate": enumerate_sample, "whole_graph": whole_graph_sample, "importance": importance_sample, "rejection": rejection_sample}
