"""Planted event pairs, noise, edge edits and recall.  All choices are hashes of ids and a seed.

Pairs are planted, disturbed and tested many at a time: every row carries its
``pair`` (which is also its seed), radius and noise, and a grid of settings runs as one plan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.stats import upper_p
from ..sources.graphs import EventGraph
from .balls import balls, cut
from .kendall import densities, kendall_test, reference_population, weighted_test
from .samplers import key, number

A, B = "a", "b"
SET = ("h", "pair", "noise", "positive")


def _key(*cols) -> Column:
    """The samplers' key, with the seed from a column."""
    return F.md5(F.concat_ws(":", *[c.cast("string") for c in cols]))


def _number(*cols) -> Column:
    return F.conv(F.substring(_key(*cols), 1, 15), 16, 10).cast("long")


def indexed(nodes: DataFrame, buckets: int = 64) -> DataFrame:
    """(id, i): nodes numbered from 0, by hash bucket and id; buckets' totals are summed apart."""
    b = nodes.select("id", (number(F.col("id"), F.lit("place")) % buckets).alias("b"))
    before = b.groupBy("b").agg(F.count(F.lit(1)).alias("u")).withColumn("at", F.coalesce(F.sum("u").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("b", "at")
    return b.withColumn("r", F.row_number().over(Window.partitionBy("b").orderBy("id")) - 1).join(F.broadcast(before), "b").select("id", (F.col("at") + F.col("r")).cast("long").alias("i"))


def _pick(g: EventGraph, pairs: DataFrame, tag: str, m: int, spare: int = 2) -> DataFrame:
    """(pair, id, r): per pair nodes in hash order, from a hash range that holds ``spare`` x m and more, so few rows are sorted."""
    n = g.nodes.count()
    share = min(1.0, (spare * m + 60) / max(n, 1))
    k = _key(F.col("id"), F.lit(tag), F.col("pair"))
    some = g.nodes.crossJoin(F.broadcast(pairs)).withColumn("k", k)
    if share < 1:
        some = some.where(F.conv(F.substring("k", 1, 15), 16, 10).cast("long") < int(share * (1 << 60)))
    return some.withColumn("r", F.row_number().over(Window.partitionBy("pair").orderBy("k", "id"))).select("pair", "id", "r", "k")


def planted_pairs(g: EventGraph, h: int, m: int, pairs: list[int], positive: bool) -> DataFrame:
    """(pair, node, event): ``m`` random a-nodes a pair.

    Positive: each gets a b-node at distance min(h, round|x|), x normal of variance h, nearer if none is
    that far.  Negative: up to ``m`` b-nodes outside the h-vicinity of all a-nodes."""
    spark = g.nodes.sparkSession
    numbers = spark.createDataFrame([(p,) for p in pairs], "pair long")
    va = cut(_pick(g, numbers, "va", m).where(F.col("r") <= m).select("pair", F.col("id").alias("root")))
    near = balls(g.adj, va.select("root").distinct(), h).join(va, "root")
    if positive:
        u = lambda tag: (_number(F.col("root"), F.lit(tag), F.col("pair")) + 1) / F.lit(float(1 << 60))
        x = F.sqrt(-2 * F.log(u("r"))) * F.cos(2 * F.pi() * u("p")) * F.lit(h**0.5)
        near = near.where(F.col("dist") <= F.least(F.lit(h), F.round(F.abs(x))))
        w = Window.partitionBy("pair", "root").orderBy(F.desc("dist"), _key(F.col("root"), F.col("node"), F.col("pair")))
        vb = near.withColumn("r", F.row_number().over(w)).where("r = 1").select("pair", "node")
    else:
        out = _pick(g, numbers, "vb", m, spare=20).join(near.select("pair", F.col("node").alias("id")).distinct(), ["pair", "id"], "left_anti")
        vb = out.withColumn("r", F.row_number().over(Window.partitionBy("pair").orderBy("k", "id"))).where(F.col("r") <= m).select("pair", F.col("id").alias("node"))
    return va.select("pair", F.col("root").alias("node"), F.lit(A).alias("event")).union(vb.select("pair", "node", F.lit(B))).distinct()


def _one(occ: DataFrame) -> DataFrame:
    return occ.select("node", "event")


def planted_positive(g: EventGraph, h: int, m: int, seed: int = 42) -> DataFrame:
    return _one(planted_pairs(g, h, m, [seed], True))


def planted_negative(g: EventGraph, h: int, m: int, seed: int = 42) -> DataFrame:
    return _one(planted_pairs(g, h, m, [seed], False))


def independent_pairs(g: EventGraph, m: int, pairs: list[int]) -> DataFrame:
    """(pair, node, event): ``m`` random nodes for either event."""
    numbers = g.nodes.sparkSession.createDataFrame([(p,) for p in pairs], "pair long")
    side = lambda tag: _pick(g, numbers, tag, m).where(F.col("r") <= m).select("pair", F.col("id").alias("node"), F.lit(tag[1]).alias("event"))
    return side("va").union(side("vb"))


def independent(g: EventGraph, m: int, seed: int = 42) -> DataFrame:
    return _one(independent_pairs(g, m, [seed]))


def noisy_pairs(g: EventGraph, occ: DataFrame, h: int, noise: list[float], positive: bool) -> DataFrame:
    """occ(pair, node, event) at each noise: (pair, noise, node, event).

    Each b-node moves with chance ``noise``: in positive pairs to a node outside the
    a-nodes' vicinity, no two to the same; in negative ones onto an a-node drawn for it."""
    spark = occ.sparkSession
    levels = F.broadcast(spark.createDataFrame([(float(p),) for p in noise], "noise double"))
    va, vb = (occ.where(F.col("event") == e).select("pair", "node") for e in (A, B))
    vb = vb.crossJoin(levels).withColumn("moves", _number(F.col("node"), F.lit("noise"), F.col("pair")) % 1000 < F.round(F.col("noise") * 1000))
    stay, gone = vb.where("NOT moves").select("pair", "noise", "node"), vb.where("moves").select("pair", "noise", "node")
    if positive:
        order = Window.partitionBy("pair", "noise").orderBy(_key(F.col("node"), F.lit("move"), F.col("pair")), "node")
        near = balls(g.adj, va.select(F.col("node").alias("root")).distinct(), h).join(va.select("pair", F.col("node").alias("root")), "root").select("pair", F.col("node").alias("id")).distinct()
        most = max(1, vb.where("moves").groupBy("pair", "noise").count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0])
        free = _pick(g, occ.select("pair").distinct(), "to", most, spare=20).join(near, ["pair", "id"], "left_anti")
        free = free.withColumn("r", F.row_number().over(Window.partitionBy("pair").orderBy("k", "id"))).select("pair", "r", F.col("id").alias("to"))
        moved = gone.withColumn("r", F.row_number().over(order)).join(free, ["pair", "r"]).select("pair", "noise", F.col("to").alias("node"))
    else:
        ranked = va.withColumn("r", F.row_number().over(Window.partitionBy("pair").orderBy("node")) - 1)
        sizes = va.groupBy("pair").agg(F.count(F.lit(1)).alias("u"))
        at = gone.join(sizes, "pair").withColumn("r", (_number(F.col("node"), F.lit("to"), F.col("pair")) % F.col("u")).cast("int"))
        moved = at.select("pair", "noise", "r").join(ranked, ["pair", "r"]).select("pair", "noise", "node")
    b = stay.union(moved).distinct().withColumn("event", F.lit(B))
    return va.crossJoin(levels).select("pair", "noise", "node", F.lit(A).alias("event")).union(b)


def with_noise(g: EventGraph, occ: DataFrame, h: int, p: float, positive: bool, seed: int = 42) -> DataFrame:
    return _one(noisy_pairs(g, occ.withColumn("pair", F.lit(seed).cast("long")), h, [p], positive))


def edit_edges(g: EventGraph, percent: int, seed: int = 42) -> EventGraph:
    """Drop (negative) or add (positive) ``percent`` of the edges; nodes stay.

    Added edges join two nodes drawn by number, uniformly; loops, repeats and edges that are there already fall away."""
    if percent <= 0:
        edges = g.edges.where(number(F.col("src"), F.col("dst"), seed=seed) % 100 >= -percent)
    else:
        n, m = g.nodes.count(), g.edges.count()
        at = indexed(g.nodes)
        draws = g.nodes.sparkSession.range(1, m * percent // 100 + 1).select(*((number(F.col("id"), F.lit(t), seed=seed) % max(n, 1)).alias(t) for t in ("u", "v")))
        ends = draws.join(at.select(F.col("i").alias("u"), F.col("id").alias("x")), "u").join(at.select(F.col("i").alias("v"), F.col("id").alias("y")), "v").where("x <> y")
        edges = g.edges.union(ends.select(F.least("x", "y"), F.greatest("x", "y"))).distinct()
    return EventGraph(g.nodes, edges, g.occ)


def detect(g: EventGraph, occ: DataFrame, h: int, n: int, sampler=None, seed: int = 42) -> DataFrame:
    """Test of one planted pair on at most ``n`` references; by the reweighted estimate if the sampler weighs them."""
    g = g.with_occ(cut(occ))
    if sampler is None:
        refs = reference_population(g, A, B, h).select("node").orderBy(key(F.col("node"), seed=seed)).limit(n)
        return kendall_test(densities(g, cut(refs), A, B, h))
    refs = cut(sampler(g, A, B, h, n, seed=seed).select("node", "w"))
    dens = densities(g, refs, A, B, h)
    return weighted_test(dens.join(refs, "node")) if sampler.__name__ == "importance_sample" else kendall_test(dens)


def _drawn(ev: DataFrame, reach: DataFrame, n: int, k: int) -> DataFrame:
    """Importance draws for all sets at once: (set, node, w) of each set's first ``n`` distinct nodes, or of all it has.

    reach(h, root, node, pos, size) are the balls of the event nodes, members in hash order."""
    spark = ev.sparkSession
    own = ev.select(*SET, F.col("node").alias("root")).join(reach.select("h", "root", "size").distinct(), ["h", "root"])
    w = Window.partitionBy(*SET).orderBy("root")
    iv = cut(own.withColumn("lo", F.sum("size").over(w) - F.col("size")))
    sets = cut(iv.groupBy(*SET).agg(F.sum("size").alias("total"), F.count(F.lit(1)).alias("m")))
    pop = ev.select(*SET, F.col("node").alias("root")).join(reach, ["h", "root"]).groupBy(*SET).agg(F.least(F.lit(n), F.count_distinct("node")).alias("want"))
    open_, done, lot, kept = cut(sets.join(pop, list(SET))), 0, max(16, 2 * n // k), None
    while open_.count():
        x = open_.crossJoin(spark.range(done + 1, done + lot + 1).withColumnRenamed("id", "j"))
        x = x.withColumn("x", _number(F.col("j"), F.col("pair"), F.col("h"), F.lit("draw")) % F.col("total")).withColumn("width", F.expr("total div m"))
        x = x.withColumn("bin", F.expr("x div width"))
        bins = iv.join(sets, list(SET)).withColumn("width", F.expr("total div m")).withColumn("bin", F.explode(F.expr("sequence(lo div width, (lo + size - 1) div width)")))
        hit = x.select(*SET, "j", "x", "bin").join(bins.select(*SET, "root", "size", "lo", "bin"), [*SET, "bin"]).where("x >= lo AND x < lo + size")
        hit = hit.withColumn("i", F.explode(F.sequence(F.lit(1), F.lit(k))))
        hit = hit.withColumn("pos", F.when(F.col("i") == 1, F.col("x") - F.col("lo")).otherwise(_number(F.col("j"), F.col("i"), F.col("pair"), F.col("h")) % F.col("size")))
        new = hit.join(reach.select("h", "root", "pos", "node"), ["h", "root", "pos"]).select(*SET, "node", (F.col("j") * 100 + F.col("i")).alias("at"))
        kept = cut(new if kept is None else kept.unionByName(new))
        got = kept.groupBy(*SET).agg(F.count_distinct("node").alias("got"))
        open_ = cut(open_.join(got, list(SET)).where("got < want").drop("got"))
        done, lot = done + lot, 2 * lot
    firsts = kept.groupBy(*SET, "node").agg(F.min("at").alias("f"))
    last = firsts.withColumn("r", F.row_number().over(Window.partitionBy(*SET).orderBy("f"))).where(F.col("r") <= n).groupBy(*SET).agg(F.max("f").alias("last"))
    return kept.join(last, list(SET)).where("at <= last").groupBy(*SET, "node").agg(F.count(F.lit(1)).alias("w"))


def test_sets(g: EventGraph, ev: DataFrame, n: int, sampler: str = "enumerate", k: int = 1) -> DataFrame:
    """ev(h, pair, noise, positive, node, event) -> one test a set, on at most ``n`` references each.

    Searches from all event nodes and from all references serve every set and radius."""
    spark = g.nodes.sparkSession
    hs = [r[0] for r in ev.select("h").distinct().collect()]  # radii
    ev = cut(ev.groupBy(*SET, "node").agg(F.max(F.col("event") == A).alias("has_a"), F.max(F.col("event") == B).alias("has_b")))
    radii = F.broadcast(spark.createDataFrame([(h,) for h in hs], "h int"))

    def within(roots: DataFrame) -> DataFrame:
        return balls(g.adj, roots, max(hs)).join(radii, F.col("dist") <= F.col("h")).select("h", "root", "node")

    reach = within(ev.select(F.col("node").alias("root")).distinct())
    if sampler == "importance":
        order = Window.partitionBy("h", "root")
        reach = cut(reach.withColumn("pos", F.row_number().over(order.orderBy(_key(F.col("node"), F.lit(42)), "node")) - 1).withColumn("size", F.count(F.lit(1)).over(order)))
        refs = _drawn(ev, reach, n, k)
    else:
        pop = ev.select(*SET, F.col("node").alias("root")).join(reach, ["h", "root"]).select(*SET, "node").distinct()
        order = Window.partitionBy(*SET).orderBy(_key(F.col("node"), F.lit(sampler), F.col("pair")), "node")
        refs = pop.withColumn("r", F.row_number().over(order)).where(F.col("r") <= n).select(*SET, "node", F.lit(1).cast("long").alias("w"))
    refs = cut(refs)
    seen = cut(within(refs.select(F.col("node").alias("root")).distinct()))
    sizes = seen.groupBy("h", "root").agg(F.count(F.lit(1)).alias("size"))
    met = refs.select(*SET, F.col("node").alias("root"), "w").join(seen, ["h", "root"]).join(ev, [*SET, "node"])
    dens = met.groupBy(*SET, "root", "w").agg(F.count_if("has_a").alias("cnt_a"), F.count_if("has_b").alias("cnt_b"), F.count(F.lit(1)).alias("c")).join(sizes, ["h", "root"])
    return (weighted_test if sampler == "importance" else kendall_test)(dens, *SET)


def recall_grid(g: EventGraph, hs, m: int, n: int, pairs: int, noise=(0.0,), signs=(True, False), sampler: str = "enumerate", k: int = 1, percent: int = 0, first: int = 100) -> DataFrame:
    """(sampler, k, percent, n, positive, h, noise, pairs, recall, mean_z): share of planted pairs found with the right sign at 5 %, one tail.

    Pairs that can't be planted, as a-nodes' vicinities cover the graph, are not counted."""
    tested = EventGraph(g.nodes, cut(edit_edges(g, percent).edges), g.occ) if percent else g
    ids = list(range(first, first + pairs))
    parts = []
    for positive in signs:
        for h in hs:
            occ = cut(planted_pairs(g, h, m, ids, positive))
            parts.append(noisy_pairs(g, occ, h, list(noise), positive).select(F.lit(h).alias("h"), "pair", "noise", F.lit(positive).alias("positive"), "node", "event"))
    ev = parts[0]
    for p in parts[1:]:
        ev = ev.unionByName(p)
    ev = cut(ev)
    both = ev.groupBy(*SET).agg(F.count_distinct("event").alias("e")).where("e = 2").select(*SET)
    r = test_sets(tested, ev.join(both, list(SET)), n, sampler, k)
    good = F.when(F.col("positive"), F.col("z")).otherwise(-F.col("z"))
    r = r.withColumn("found", F.coalesce(upper_p(good) < 0.05, F.lit(False)).cast("double"))
    head = [F.lit(sampler).alias("sampler"), F.lit(k).alias("k"), F.lit(percent).alias("percent"), F.lit(n).alias("n")]
    return r.groupBy("positive", "h", "noise").agg(F.count(F.lit(1)).alias("pairs"), F.avg("found").alias("recall"), F.avg("z").alias("mean_z")).select(*head, "positive", "h", "noise", "pairs", "recall", "mean_z")


def error_rates(g: EventGraph, hs, m: int, n: int, pairs: int, first: int = 100) -> DataFrame:
    """(h, pairs, upper, lower, mean_z): how often independent events pass either one-tailed test at 5 %."""
    occ = cut(independent_pairs(g, m, list(range(first, first + pairs))))
    levels = F.broadcast(occ.sparkSession.createDataFrame([(h,) for h in hs], "h int"))
    ev = occ.crossJoin(levels).select("h", "pair", F.lit(0.0).alias("noise"), F.lit(True).alias("positive"), "node", "event")
    z = F.col("z")
    share = lambda x: F.avg(F.coalesce(upper_p(x) < 0.05, F.lit(False)).cast("double"))
    return test_sets(g, ev, n).groupBy("h").agg(F.count(F.lit(1)).alias("pairs"), share(z).alias("upper"), share(-z).alias("lower"), F.avg("z").alias("mean_z"))


def calibrate_n(g: EventGraph, h: int, m: int, pairs: int = 20, target: float = 0.95, sizes=(50, 100, 300, 900)) -> DataFrame:
    """(n, recall): growing samples until planted positive pairs are found often enough."""
    rows = []
    for n in sizes:
        r = recall_grid(g, (h,), m, n, pairs, signs=(True,)).first()
        rows.append((n, float(r.recall)))
        if r.recall >= target:
            break
    return g.nodes.sparkSession.createDataFrame(rows, "n int, recall double")
