"""Measures to compare with: transaction correlation, proximity patterns, distances, walks, landmarks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import EventGraph
from .balls import balls, cut, set_ball
from .kendall import value_test
from .samplers import key, number


def transaction_measures(g: EventGraph, a: str, b: str) -> DataFrame:
    """Every node a transaction: counts, s, tau_b, z, lift, support, confidence, jaccard, cosine, chi2, from one 2 x 2 table."""
    n11, na, nb, n = F.col("n11"), F.col("na"), F.col("nb"), F.col("n").cast("double")
    t = g.event_nodes(a, b).agg(F.count_if(F.col("has_a") & F.col("has_b")).alias("n11"), F.count_if("has_a").alias("na"), F.count_if("has_b").alias("nb")).crossJoin(g.nodes.agg(F.count(F.lit(1)).alias("n")))
    s = n11 * (F.col("n") - na - nb + n11) - (na - n11) * (nb - n11)
    t = t.withColumn("s", s)
    d = {x: (c.cast("double"), (F.col("n") - c).cast("double")) for x, c in (("a", na), ("b", nb))}
    tie = lambda x, f: f(d[x][0]) + f(d[x][1])
    t2, t3, t5 = lambda u: u * (u - 1), lambda u: u * (u - 1) * (u - 2), lambda u: u * (u - 1) * (2 * u + 5)
    var = (n * (n - 1) * (2 * n + 5) - tie("a", t5) - tie("b", t5)) / 18 + tie("a", t3) * tie("b", t3) / (9 * n * (n - 1) * (n - 2)) + tie("a", t2) * tie("b", t2) / (2 * n * (n - 1))
    q = F.sqrt(d["a"][0] * d["a"][1] * d["b"][0] * d["b"][1])
    ok = q > 0
    return t.select(
        "n", "na", "nb", "n11", "s",
        F.when(ok, F.col("s") / q).alias("tau_b"), F.when(ok, F.col("s") / F.sqrt(var)).alias("z"),
        F.when(ok, n11 * n / (d["a"][0] * d["b"][0])).alias("lift"), (n11 / n).alias("support"), F.when(na > 0, n11 / na).alias("confidence"),
        F.when(na + nb > 0, n11 / (na + nb - n11)).alias("jaccard"), F.when(ok, n11 / F.sqrt(d["a"][0] * d["b"][0])).alias("cosine"),
        F.when(ok, n * F.col("s") / q * F.col("s") / q).alias("chi2"),
    )


def reaches(g: EventGraph, alpha: float = 1.0, eps: float = 0.12) -> DataFrame:
    """(node, event, reach): e^(-alpha dist) to the event's nearest occurrence, dropped below ``eps``.

    All events travel together, a row for each (event, node), as roots of one search."""
    hops = 0
    while 2.718281828459045 ** (-alpha * (hops + 1)) >= eps:
        hops += 1
    near = g.occ.select("event", "node", F.lit(0).alias("dist"))
    front = near
    for d in range(1, hops + 1):
        step = front.join(g.adj, F.col("node") == F.col("u")).select("event", F.col("v").alias("node")).distinct()
        front = step.join(near.select("event", "node"), ["event", "node"], "left_anti").withColumn("dist", F.lit(d))
        near = near.unionByName(front)
    return near.select("node", "event", F.exp(-alpha * F.col("dist")).alias("reach"))


def proximity_pairs(g: EventGraph, alpha: float = 1.0, eps: float = 0.12, least: float = 10.0) -> DataFrame:
    """(a, b, support): mean over nodes of the product of reaches, at least ``least`` / nodes."""
    r = reaches(g, alpha, eps)
    both = r.toDF("node", "a", "ra").join(r.toDF("node", "b", "rb"), "node").where("a < b").groupBy("a", "b").agg(F.sum(F.col("ra") * F.col("rb")).alias("total"))
    return both.where(F.col("total") >= least).crossJoin(g.nodes.agg(F.count(F.lit(1)).alias("n"))).select("a", "b", (F.col("total") / F.col("n")).alias("support"))


def proximity_sets(g: EventGraph, alpha: float = 1.0, eps: float = 0.12, least: float = 10.0, sep: str = "|") -> DataFrame:
    """(items, size, support): all sets of two and more events with support at least ``least`` / nodes, level by level until none is left.

    A level joins sets that differ in their last event alone; a set's products over
    the nodes that it reaches go on to the next level."""
    r = cut(reaches(g, alpha, eps))
    level = r.select("node", F.array("event").alias("items"), F.col("reach").alias("prod"))
    frequent, found, size = level.select("items").distinct(), None, 1
    while True:
        head = F.slice("items", 1, size - 1) if size > 1 else F.array().cast("array<string>")
        ends = frequent.select(F.array_join(head, sep).alias("head"), "items", F.element_at("items", -1).alias("last"))
        wider = ends.join(ends.select("head", F.col("last").alias("event")), "head").where("last < event").select("items", "event")
        rows = level.join(wider, "items").join(r, ["node", "event"]).select("node", F.concat("items", F.array("event")).alias("items"), (F.col("prod") * F.col("reach")).alias("prod"))
        total = cut(rows.groupBy("items").agg(F.sum("prod").alias("total")).where(F.col("total") >= least))
        if not total.count():
            break
        found = total if found is None else found.unionByName(total)
        frequent = total.select("items")
        level, size = cut(rows.join(frequent, "items", "left_semi").select("node", "items", "prod")), size + 1
    if found is None:
        return g.nodes.sparkSession.createDataFrame([], "items string, size int, support double")
    return found.crossJoin(g.nodes.agg(F.count(F.lit(1)).alias("n"))).select(F.array_join("items", sep).alias("items"), F.size("items").alias("size"), (F.col("total") / F.col("n")).alias("support"))


def average_distance(g: EventGraph, a: str, b: str, d_max: int = 4) -> DataFrame:
    """Mean hops from a-nodes to the nearest b-node, and back; farther than ``d_max`` counts as d_max + 1."""
    out = None
    for x, y, name in ((a, b, "a_to_b"), (b, a, "b_to_a")):
        near = set_ball(g.adj, g.occ.where(F.col("event") == y), d_max)
        d = g.occ.where(F.col("event") == x).join(near, "node", "left").agg(F.avg(F.coalesce("dist", F.lit(d_max + 1))).alias(name))
        out = d if out is None else out.crossJoin(d)
    return out


def distance_permutation(g: EventGraph, a: str, b: str, d_max: int = 3, rounds: int = 50, seed: int = 42) -> DataFrame:
    """Randomisation null of the mean distance: (observed, mean, sd, z, p_low) over ``rounds`` relabelings of b of the same size.

    All relabelings run in one search, keyed by round."""
    nb = g.occ.where(F.col("event") == b).count()
    spark = g.nodes.sparkSession
    draws = spark.range(rounds).select((F.col("id") + 1).alias("event"))
    # a round sorts only the nodes in a hash range that holds twice those wanted and more
    share = min(1.0, (2 * nb + 60) / max(g.nodes.count(), 1))
    some = g.nodes.crossJoin(F.broadcast(draws)).where(number(F.col("id"), F.col("event"), seed=seed) < int(share * (1 << 60)))
    pick = some.withColumn("r", F.row_number().over(Window.partitionBy("event").orderBy(key(F.col("id"), F.col("event"), seed=seed), "id"))).where(F.col("r") <= nb)
    seeds = pick.select("event", F.col("id").alias("node")).union(g.occ.where(F.col("event") == b).select(F.lit(0).cast("long"), "node"))
    near = front = seeds.withColumn("dist", F.lit(0))
    for d in range(1, d_max + 1):
        step = front.join(g.adj, F.col("node") == F.col("u")).select("event", F.col("v").alias("node")).distinct()
        front = step.join(near.select("event", "node"), ["event", "node"], "left_anti").withColumn("dist", F.lit(d))
        near = cut(near.unionByName(front))
        front = near.where(F.col("dist") == d)
    all_a = g.occ.where(F.col("event") == a).select("node").crossJoin(draws.union(spark.range(1)))
    means = all_a.join(near, ["event", "node"], "left").groupBy("event").agg(F.avg(F.coalesce("dist", F.lit(d_max + 1))).alias("m"))
    seen = F.max(F.when(F.col("event") == 0, F.col("m")))
    m = means.agg(seen.alias("observed"), F.avg(F.when(F.col("event") > 0, F.col("m"))).alias("mean"), F.stddev(F.when(F.col("event") > 0, F.col("m"))).alias("sd"))
    low = means.crossJoin(m.select("observed")).agg(((F.count_if((F.col("event") > 0) & (F.col("m") <= F.col("observed"))) + 1) / (rounds + 1)).alias("p_low"))
    return m.crossJoin(low).select("observed", "mean", "sd", F.when(F.col("sd") > 0, (F.col("observed") - F.col("mean")) / F.col("sd")).alias("z"), "p_low")


def hitting_time(g: EventGraph, target: DataFrame, rounds: int = 5) -> DataFrame:
    """(node, g, proximity): expected steps of a uniform walk to ``target``, cut off at ``rounds``; proximity = 1 - g / rounds."""
    nodes = g.nodes.select(F.col("id").alias("node")).join(target.select("node", F.lit(True).alias("at")).distinct(), "node", "left")
    now = nodes.select("node", F.lit(0.0).alias("g"))
    for i in range(rounds):
        step = g.adj.join(now, F.col("v") == F.col("node")).groupBy(F.col("u").alias("node")).agg(F.avg("g").alias("m"))
        now = nodes.join(step, "node", "left").select("node", F.when(F.col("at"), 0.0).when(F.col("m").isNull(), float(i + 1)).otherwise(1 + F.col("m")).alias("g"))
        if i % 3 == 2:
            now = cut(now)
    return now.select("node", "g", (1 - F.col("g") / rounds).alias("proximity"))


def personal_pagerank(g: EventGraph, roots: DataFrame, rounds: int = 4, restart: float = 0.15) -> DataFrame:
    """(root, node, p): power rounds of a walk that returns to its root."""
    deg = g.adj.groupBy("u").agg(F.count(F.lit(1)).alias("deg"))
    arcs = g.adj.join(deg, "u")
    start = roots.select("root", F.col("root").alias("node"), F.lit(1.0).alias("p"))
    now = start
    for i in range(rounds):
        step = now.join(arcs, now.node == arcs.u).select("root", F.col("v").alias("node"), (F.col("p") * (1 - restart) / F.col("deg")).alias("p"))
        now = step.unionByName(start.withColumn("p", F.lit(restart))).groupBy("root", "node").agg(F.sum("p").alias("p"))
        if i % 2:
            now = cut(now)
    return now


def ppr_densities(g: EventGraph, refs: DataFrame, a: str, b: str, **kw) -> DataFrame:
    """(node, da, db): walk mass on the nodes of either event, an alternative density."""
    p = personal_pagerank(g, refs.select(F.col("node").alias("root")), **kw).join(g.event_nodes(a, b), "node")
    return p.groupBy(F.col("root").alias("node")).agg(F.sum(F.when(F.col("has_a"), F.col("p")).otherwise(0)).alias("da"), F.sum(F.when(F.col("has_b"), F.col("p")).otherwise(0)).alias("db"))


def self_correlation(g: EventGraph, event: str, rounds: int = 5, trials: int = 5, seed: int = 42) -> DataFrame:
    """(trial, proximity): mean over neighbours of an event's nodes of walk proximity to it; trial 0 is the event, others are random sets of its size."""
    own = g.occ.where(F.col("event") == event).select("node")
    n = own.count()
    out = None
    for t in range(trials + 1):
        s = own if t == 0 else g.nodes.orderBy(key(F.col("id"), F.lit(t), seed=seed)).limit(n).select(F.col("id").alias("node"))
        near = s.join(g.adj, F.col("node") == F.col("u")).select(F.col("v").alias("node"))
        m = hitting_time(g, s, rounds).join(near, "node").agg(F.lit(t).alias("trial"), F.avg("proximity").alias("proximity"))
        out = m if out is None else out.unionByName(m)
    return out


def landmark_coordinates(g: EventGraph, k: int = 4, d_max: int = 4, seed: int = 42) -> DataFrame:
    """(node, coords): hops to ``k`` landmarks, d_max + 1 beyond."""
    marks = g.nodes.orderBy(key(F.col("id"), F.lit("mark"), seed=seed)).limit(k).withColumn("i", F.row_number().over(Window.orderBy("id")) - 1)
    d = balls(g.adj, marks.select(F.col("id").alias("root")), d_max).join(marks, F.col("root") == F.col("id")).select("node", "i", "dist")
    got = d.groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct("i", "dist"))).alias("m"))
    return g.nodes.select(F.col("id").alias("node")).join(got, "node", "left").select("node", F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(d_max + 1))).alias("coords"))


def landmark_densities(g: EventGraph, refs: DataFrame, a: str, b: str, k: int = 4, d_max: int = 4) -> DataFrame:
    """(node, da, db, distances): kernel densities by coordinate distance, and how many distances that took.

    Nodes with equal coordinates are one point, so the product runs over distinct points of the event nodes."""
    at = landmark_coordinates(g, k, d_max)
    points = g.event_nodes(a, b).join(at, "node").groupBy("coords").agg(F.count_if("has_a").alias("na"), F.count_if("has_b").alias("nb"))
    r = refs.select("node").join(at, "node")
    gap = F.sqrt(F.aggregate(F.zip_with(F.col("coords"), F.col("c2"), lambda x, y: (x - y) * (x - y)), F.lit(0), lambda s, x: s + x))
    both = r.crossJoin(points.withColumnRenamed("coords", "c2"))
    w = F.exp(-gap)
    return both.groupBy("node").agg(F.sum(w * F.col("na")).alias("da"), F.sum(w * F.col("nb")).alias("db"), F.count(F.lit(1)).alias("distances"))


def embedding_test(g: EventGraph, refs: DataFrame, a: str, b: str, k: int = 4, d_max: int = 4) -> DataFrame:
    """The Kendall test on kernel densities by coordinate distance."""
    return value_test(landmark_densities(g, refs, a, b, k, d_max))
