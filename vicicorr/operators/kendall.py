"""Densities of two events about reference nodes and the Kendall test on them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.stats import upper_p, var_with_ties, verdict
from ..sources.graphs import EventGraph
from .balls import balls, cut, set_ball
from .skeleton import ball_counts

PAIRS_UP_TO = 20_000  # distinct density pairs; beyond, the rank grid


def reference_population(g: EventGraph, a: str, b: str, h: int) -> DataFrame:
    """(node, dist): nodes that see either event within ``h`` hops."""
    return set_ball(g.adj, g.event_nodes(a, b), h)


def out_of_sight(g: EventGraph, a: str, b: str, h: int) -> DataFrame:
    return g.nodes.select(F.col("id").alias("node")).join(reference_population(g, a, b, h), "node", "left_anti")


def densities(g: EventGraph, refs: DataFrame, a: str, b: str, h: int) -> DataFrame:
    """(node, size, cnt_a, cnt_b, c): ball size, nodes of either event, and of any, for each reference.

    One hop needs no search: a ball is the node and its distinct neighbours.  From two
    hops on the references travel as bits of masks, on the graph's skeleton."""
    flags = g.event_nodes(a, b)
    if h >= 2:
        return ball_counts(g, refs.select(F.col("node").alias("root")), flags.toDF("node", "cnt_a", "cnt_b"), h).withColumnRenamed("root", "node")
    reach = refs.select(F.col("node").alias("root"), "node")
    if h:
        reach = reach.unionByName(reach.select("root").join(g.adj, F.col("root") == F.col("u")).select("root", F.col("v").alias("node")))
    both = reach.join(flags, "node", "left")
    return both.groupBy("root").agg(F.count(F.lit(1)).alias("size"), F.count_if("has_a").alias("cnt_a"), F.count_if("has_b").alias("cnt_b"), F.count("has_a").alias("c")).withColumnRenamed("root", "node")


def weighted_densities(g: EventGraph, refs: DataFrame, a: str, b: str, h: int, intensity: DataFrame | None = None, decay: float = 1.0) -> DataFrame:
    """(node, size, da, db): densities that count an event node by its intensity(node, event, q) and by ``decay`` for each hop."""
    q = (g.occ.withColumn("q", F.lit(1.0)) if intensity is None else intensity).where(F.col("event").isin(a, b)).groupBy("node").agg(*(F.sum(F.when(F.col("event") == e, F.col("q").cast("double"))).alias(k) for e, k in ((a, "qa"), (b, "qb"))))
    reach = balls(g.adj, refs.select(F.col("node").alias("root")), h).join(q, "node", "left")
    mass = lambda k: F.sum(F.coalesce(F.col(k), F.lit(0.0)) * F.pow(F.lit(decay), F.col("dist"))) / F.count(F.lit(1))
    return reach.groupBy("root").agg(F.count(F.lit(1)).alias("size"), mass("qa").alias("da"), mass("qb").alias("db")).withColumnRenamed("root", "node")


def value_test(values: DataFrame, *by: str, digits: int = 9, **kw) -> DataFrame:
    """The test on any two numbers (da, db) a reference; equal to ``digits`` places counts as a tie."""
    whole = lambda c: F.round(F.col(c) * F.lit(10.0**digits)).cast("long")
    return kendall_test(values.select(*by, F.lit(1).cast("long").alias("size"), whole("da").alias("cnt_a"), whole("db").alias("cnt_b")), *by, **kw)


def profile(g: EventGraph, refs: DataFrame, a: str, b: str, hs: tuple[int, ...]) -> DataFrame:
    """Densities for several radii from one search: (h, node, size, cnt_a, cnt_b, c)."""
    reach = balls(g.adj, refs.select(F.col("node").alias("root")), max(hs)).join(g.event_nodes(a, b), "node", "left")
    reach = reach.withColumn("h", F.explode(F.filter(F.array(*(F.lit(h) for h in hs)), lambda h: h >= F.col("dist"))))
    return reach.groupBy("h", "root").agg(F.count(F.lit(1)).alias("size"), F.count_if("has_a").alias("cnt_a"), F.count_if("has_b").alias("cnt_b"), F.count("has_a").alias("c")).withColumnRenamed("root", "node")


def vote(cnt_a1, size1, cnt_b1, cnt_a2, size2, cnt_b2) -> Column:
    """+1, -1 or 0 as the two densities move together, apart or tie; exact, by cross products."""
    side = lambda x1, x2: F.signum(x1.cast("decimal(38,0)") * size2 - x2.cast("decimal(38,0)") * size1)
    return (side(cnt_a1, cnt_a2) * side(cnt_b1, cnt_b2)).cast("int")


def cells(dens: DataFrame, *by: str) -> DataFrame:
    """Distinct pairs of densities with their number; equal rationals give equal quotients (sizes below 2**26)."""
    return dens.groupBy(*by, (F.col("cnt_a") / F.col("size")).alias("da"), (F.col("cnt_b") / F.col("size")).alias("db")).agg(F.count(F.lit(1)).alias("w"))


def pair_counts(dens: DataFrame, *by: str) -> DataFrame:
    """concordant, discordant, tied in a only, in b only, in both; over cells, not nodes, so ties cost nothing."""
    c = cells(dens, *by)
    x, y = (c.select(*by, *(F.col(k).alias(f"{k}{i}") for k in ("da", "db", "w"))) for i in "12")
    later = (F.col("da1") < F.col("da2")) | ((F.col("da1") == F.col("da2")) & (F.col("db1") < F.col("db2")))
    pairs = x.join(y, [x[k].eqNullSafe(y[k]) for k in by] + [later] if by else later)
    pairs = pairs.select(*(x[k] for k in by), F.signum(F.col("da1") - F.col("da2")).alias("sa"), F.signum(F.col("db1") - F.col("db2")).alias("sb"), (F.col("w1") * F.col("w2")).alias("n"))
    n = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0)).cast("long")
    cross = pairs.groupBy(*by).agg(n(F.col("sa") * F.col("sb") > 0).alias("concordant"), n(F.col("sa") * F.col("sb") < 0).alias("discordant"), n((F.col("sa") == 0) & (F.col("sb") != 0)).alias("tied_a"), n((F.col("sa") != 0) & (F.col("sb") == 0)).alias("tied_b"))
    same = c.groupBy(*by).agg(F.sum((F.col("w") * (F.col("w") - 1) / 2).cast("long")).alias("tied_both"), F.sum("w").alias("n"))
    out = same.join(cross, list(by), "left") if by else same.crossJoin(cross)
    return out.select(*by, "n", *(F.coalesce(k, F.lit(0)).cast("long").alias(k) for k in ("concordant", "discordant", "tied_a", "tied_b", "tied_both")))


def tie_sums(dens: DataFrame, side: str, *by: str) -> DataFrame:
    u = F.col("u").cast("decimal(38,0)")
    groups = dens.groupBy(*by, (F.col(f"cnt_{side}") / F.col("size")).alias("d")).agg(F.count(F.lit(1)).alias("u"))
    total = lambda x, name: F.sum(x).cast("double").alias(f"{name}_{side}")
    return groups.groupBy(*by).agg(total(u * (u - 1), "t2"), total(u * (u - 1) * (u - 2), "t3"), total(u * (u - 1) * (2 * u + 5), "t5"))


def kendall_test(dens: DataFrame, *by: str, alpha: float = 0.05) -> DataFrame:
    """One row (a group ``by``): n, s, t, var_s, z, p_upper, p_lower, verdict.

    The densities, a few numbers a reference, are checkpointed: three aggregates
    read them, and the search behind them must not run thrice."""
    dens = cut(dens.select(*by, "size", "cnt_a", "cnt_b"))
    if not by and cells(dens).count() > PAIRS_UP_TO:
        p = dens.agg(F.count(F.lit(1)).alias("n")).crossJoin(kendall_s_grid(dens).select(F.col("s").cast("long").alias("concordant"), F.lit(0).cast("long").alias("discordant")))
    else:
        p = pair_counts(dens, *by)
    for side in "ab":
        t = tie_sums(dens, side, *by)
        p = p.join(t, list(by)) if by else p.crossJoin(t)
    s = (F.col("concordant") - F.col("discordant")).cast("long")
    sums = lambda side: {k: F.col(f"{k}_{side}") for k in ("t2", "t3", "t5")}
    p = p.withColumn("s", s).withColumn("var_s", var_with_ties(F.col("n"), sums("a"), sums("b")))
    p = p.withColumn("t", F.when(F.col("n") > 1, F.col("s") / (F.col("n") * (F.col("n") - 1) / 2)))
    p = p.withColumn("z", F.when(F.col("var_s") > 0, F.col("s") / F.sqrt("var_s")))
    return p.select(*by, "n", "s", "t", "var_s", "z", upper_p(F.col("z")).alias("p_upper"), upper_p(-F.col("z")).alias("p_lower"), verdict(F.col("z"), alpha).alias("verdict"))


def weighted_tau(sample: DataFrame, *by: str) -> DataFrame:
    """Reweighted estimate from draws(node, w, size, cnt_a, cnt_b, c): weights w / c, as the draw rate is in proportion to c."""
    r = sample.select(*by, (F.col("cnt_a") / F.col("size")).alias("da"), (F.col("cnt_b") / F.col("size")).alias("db"), (F.col("w") / F.col("c")).alias("o"))
    some = r.groupBy(*by, "da", "db").agg(F.sum("o").alias("o"))
    x, y = (some.select(*by, *(F.col(k).alias(f"{k}{i}") for k in ("da", "db", "o"))) for i in "12")
    later = F.col("da1") < F.col("da2")
    votes = x.join(y, [x[k].eqNullSafe(y[k]) for k in by] + [later] if by else later).select(*(x[k] for k in by), (F.signum(F.col("db2") - F.col("db1")) * F.col("o1") * F.col("o2")).alias("v")).groupBy(*by).agg(F.sum("v").alias("v"))
    norm = r.groupBy(*by).agg(((F.sum("o") * F.sum("o") - F.sum(F.col("o") * F.col("o"))) / 2).alias("q"), F.count(F.lit(1)).alias("n"))
    out = norm.join(votes, list(by), "left") if by else norm.crossJoin(votes)
    return out.select(*by, "n", F.when(F.col("q") > 0, F.coalesce("v", F.lit(0.0)) / F.col("q")).alias("t"))


def weighted_test(sample: DataFrame, *by: str, alpha: float = 0.05) -> DataFrame:
    """The test after importance draws: n, t (reweighted), var_t, z, p_upper, p_lower, verdict.

    The variance is the tie-corrected one of the distinct references drawn, as a share of their pairs."""
    sample = cut(sample.select(*by, "w", "size", "cnt_a", "cnt_b", "c"))
    pairs = F.col("n") * (F.col("n") - 1) / 2
    var = kendall_test(sample, *by, alpha=alpha).select(*by, F.when(F.col("n") > 1, F.col("var_s") / (pairs * pairs)).alias("var_t"))
    t = weighted_tau(sample, *by)
    out = t.join(var, list(by)) if by else t.crossJoin(var)
    out = out.withColumn("z", F.when(F.col("var_t") > 0, F.col("t") / F.sqrt("var_t")))
    return out.select(*by, "n", "t", "var_t", "z", upper_p(F.col("z")).alias("p_upper"), upper_p(-F.col("z")).alias("p_lower"), verdict(F.col("z"), alpha).alias("verdict"))


def inversions(r: np.ndarray) -> int:
    """Pairs i < j with r[i] > r[j], by merging halves of growing width."""
    n, total, width = len(r), 0, 1
    place = np.arange(n)
    while width < n:
        block, right = place // (2 * width), place // width % 2
        order = np.lexsort((right, r, block))
        left, b = 1 - right[order], block[order]
        head = np.flatnonzero(np.r_[True, b[1:] != b[:-1]])
        size = np.diff(np.r_[head, n])
        upto = np.cumsum(left)
        before = upto - np.repeat(upto[head] - left[head], size)
        total += int(((np.repeat(np.add.reduceat(left, head), size) - before) * (1 - left)).sum())
        width *= 2
    return total


def block_sum(a: np.ndarray, b: np.ndarray) -> int:
    """Vote sum of one block: pairs less twice the inversions of b in order of (a, b), ties taken off."""
    if len(a) < 2:
        return 0
    if len(a) <= 512:  # few: each with each
        return int((np.sign(a[:, None] - a).astype(np.int8) * np.sign(b[:, None] - b).astype(np.int8)).sum(dtype=np.int64)) // 2
    order = np.lexsort((b, a))
    ra, rb = np.unique(a, return_inverse=True)[1][order], np.unique(b, return_inverse=True)[1][order]
    two = lambda key: sum(u * (u - 1) // 2 for u in np.unique(key, return_counts=True)[1].tolist())
    return len(a) * (len(a) - 1) // 2 - two(ra) - two(rb) + two(ra * len(a) + rb) - 2 * inversions(rb)


def kendall_s_grid(dens: DataFrame, buckets: int = 64) -> DataFrame:
    """Exact vote sum for many references: (s).

    Both densities are cut in buckets at value boundaries.  Pairs apart in both
    are decided by the bucket counts (at most buckets squared, which reach the
    driver); pairs that share a bucket are summed within it by merge counting, unless
    it has a single value, such as the common zero, whose pairs are ties;
    those that share both are counted twice so and taken off once."""
    d = dens.select((F.col("cnt_a") / F.col("size")).alias("a"), (F.col("cnt_b") / F.col("size")).alias("b"))
    q = [i / buckets for i in range(1, buckets)]
    cuts = d.agg(F.percentile_approx("a", q, 10_000).alias("a"), F.percentile_approx("b", q, 10_000).alias("b")).first()
    place = lambda c: sum((F.col(c) > x).cast("int") for x in sorted(set(cuts[c] or [0.0])))
    d = d.withColumn("ka", place("a")).withColumn("kb", place("b"))
    table = d.groupBy("ka", "kb").count().collect()
    m = np.zeros((buckets + 1, buckets + 1), object)
    for ka, kb, n in table:
        m[ka, kb] = n
    left = np.cumsum(np.cumsum(m, 0), 1)
    apart = 0
    for i in range(1, buckets + 1):
        for j in range(buckets + 1):
            if m[i, j]:
                below = left[i - 1, j - 1] if j else 0
                apart += m[i, j] * (below - (left[i - 1, -1] - left[i - 1, j]))

    def local(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"s": [block_sum(pdf.a.values, pdf.b.values)]})

    def mixed(*by: str) -> DataFrame:
        """Rows of the buckets that hold more than one value of both."""
        some = d.groupBy(*by).agg(F.min("a").alias("a0"), F.max("a").alias("a1"), F.min("b").alias("b0"), F.max("b").alias("b1")).where("a0 < a1 AND b0 < b1")
        return d.join(some.select(*by), list(by), "left_semi")

    parts = mixed("ka").groupBy("ka").applyInPandas(local, "s long").union(mixed("kb").groupBy("kb").applyInPandas(local, "s long")).union(mixed("ka", "kb").groupBy("ka", "kb").applyInPandas(local, "s long").select(-F.col("s")))
    return parts.agg((F.coalesce(F.sum("s"), F.lit(0)) + F.lit(int(apart))).alias("s"))


def exact_test(g: EventGraph, a: str, b: str, h: int, include_out_of_sight: bool = False) -> DataFrame:
    """The test over all references; with nodes that see neither event it shows how these inflate z."""
    refs = g.nodes.select(F.col("id").alias("node")) if include_out_of_sight else reference_population(g, a, b, h)
    return kendall_test(densities(g, refs, a, b, h))


def spearman(dens: DataFrame) -> DataFrame:
    """Spearman's rho with average ranks; ranks come from counts of distinct values, not from sorting all rows in one task."""
    out = dens.select("node", (F.col("cnt_a") / F.col("size")).alias("da"), (F.col("cnt_b") / F.col("size")).alias("db"))
    for c in ("da", "db"):
        sizes = out.groupBy(c).agg(F.count(F.lit(1)).alias("u"))
        before = sizes.withColumn("r", F.sum("u").over(Window.orderBy(c)) - (F.col("u") - 1) / 2).select(c, F.col("r").alias(f"r_{c}"))
        out = out.join(before, c)
    return out.agg(F.count(F.lit(1)).alias("n"), F.corr("r_da", "r_db").alias("rho"))
