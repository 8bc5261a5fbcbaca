"""Experiment queries: worked toys, pairs beside their transaction correlation, costs in rows, late rows, the stored index."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import oracle as o
from .api import Pair
from .operators import baselines, index, kendall
from .operators.balls import balls, cut, set_ball
from .operators.samplers import key
from .queries import COP, A, B, Q, SQL, graph, query, tidy
from .sources import graphs
from .sources.graphs import EventGraph

# toys: cliques of six nodes in a row; events meet in the same cliques, or keep to different ones
CLIQUES = [(c * 10 + i, c * 10 + j) for c in range(4) for i in range(6) for j in range(i + 1, 6)] + [(c * 10 + 5, c * 10 + 10) for c in range(3)]
LINE = [(i, i + 1) for i in range(8)]
TOYS = {
    "toy_attract": (CLIQUES, [(1, "a"), (2, "a"), (3, "b"), (4, "b"), (11, "a"), (12, "b")]),
    "toy_repel": (CLIQUES, [(1, "a"), (2, "a"), (3, "a"), (21, "b"), (22, "b"), (11, "a"), (13, "b")]),
    "toy_line": (LINE, [(2, "a"), (3, "b")]),
    "toy_both_low": (CLIQUES, [(1, "a"), (2, "b"), (11, "a"), (12, "b")]),
    "toy_cross": (CLIQUES, [(1, "a"), (2, "a"), (11, "b"), (12, "b"), (21, "a"), (31, "b"), (32, "b")]),
}
SIGNS = ("toy_attract", "toy_repel", "toy_both_low", "toy_cross")


def _values(rows) -> str:
    return ", ".join(str(r).replace('"', "'") for r in rows)


for _n, (_pairs, _occ) in TOYS.items():
    o.GRAPHS[_n] = f"\npairs AS (SELECT x::BIGINT AS x, y::BIGINT AS y FROM (VALUES {_values(_pairs)}) t(x, y)),\nocc AS (SELECT node::BIGINT AS node, event FROM (VALUES {_values(_occ)}) t(node, event)),\nmore AS (SELECT node AS id FROM occ)"


def toy(spark, name: str) -> EventGraph:
    pairs, occ = TOYS[name]
    return graphs.from_edges(spark.createDataFrame(pairs, "x long, y long"), spark.createDataFrame(occ, "node long, event string"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("toy_scenarios", " UNION ALL ".join(f"SELECT '{t}' AS toy, * FROM ({o.exact(t, 'a', 'b', 1)})" for t in SIGNS))
def _scenarios(s, d):
    """Events that never share a node: they attract where they meet in the same cliques, repel where they don't."""
    return _union([tidy(kendall.exact_test(toy(s, t), "a", "b", 1)).select(F.lit(t).alias("toy"), "*") for t in SIGNS])


@query("toy_overlap", f"{o.dens('toy_line', 'a', 'b', 1)} SELECT node, c FROM dens")
def _overlap(s, d):
    """How many event nodes each reference sees: two overlapping balls of three share two nodes."""
    return kendall.densities(g := toy(s, "toy_line"), kendall.reference_population(g, "a", "b", 1), "a", "b", 1).select("node", "c")


# pairs on the given tables, with the transaction measure beside
POSITIVE = [(g, a, b, h) for g, a, b in (("page_path", "en", "fr"), ("doc_shingle", "q1", "t1")) for h in (1, 2, 3) if (g, h) != ("doc_shingle", 3)]
NEGATIVE = [("doc_shingle", "q0", "t1", 1), ("doc_shingle", "en", "fr", 2), *((COP, A, B, h) for h in (1, 2, 3)), *((COP, "Brand#4", "Brand#2", h) for h in (1, 2, 3))]


def _beside_sql(name: str, a: str, b: str, h: int, whole: dict[str, str] | None = None) -> str:
    g = (whole or {}).get(name, name)
    tc = f"WITH {o.graph(g)}, {o.events(a, b)}, k AS (SELECT (SELECT count(*) FROM nodes) AS n, count(*) FILTER (WHERE has_a) AS na, count(*) FILTER (WHERE has_b) AS nb, count(*) FILTER (WHERE has_a AND has_b) AS n11 FROM ev) SELECT (n11 * (n - na - nb + n11) - (na - n11) * (nb - n11))::BIGINT AS tc_s FROM k"
    return f"SELECT '{name}' AS graph, '{a}' AS a, '{b}' AS b, {h} AS h, r.n, r.s, r.z, r.verdict, q.tc_s FROM ({o.exact(g, a, b, h)}) r, ({tc}) q"


def _beside(s, d, pairs, whole: dict[str, str] | None = None) -> DataFrame:
    out = []
    for name, a, b, h in pairs:
        g = graph(s, d, (whole or {}).get(name, name))
        tc = baselines.transaction_measures(g, a, b).select(F.col("s").alias("tc_s"))
        t = tidy(kendall.exact_test(g, a, b, h)).select(F.lit(name).alias("graph"), F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(h).alias("h"), "n", "s", "z", "verdict")
        out.append(t.crossJoin(tc))  # one row each
    return _union(out)


# of documents, all shared word 4-grams count for the positive pairs
WHOLE = {"doc_shingle": "doc_shingle_all"}
graphs.BUILDERS["doc_shingle_all"] = graphs.doc_shingle_all
o.GRAPHS["doc_shingle_all"] = o.GRAPHS["doc_shingle"].replace("BETWEEN 2 AND 20", ">= 2")

query("real_positive", " UNION ALL ".join(_beside_sql(*p, WHOLE) for p in POSITIVE))(lambda s, d: _beside(s, d, POSITIVE, WHOLE))
query("real_negative", " UNION ALL ".join(_beside_sql(*p) for p in NEGATIVE))(lambda s, d: _beside(s, d, NEGATIVE))

# costs in rows touched, the same on any machine
SIZES = (20, 200, 1000)


def _va_sql(m: int) -> str:
    return f"SELECT id AS node FROM nodes ORDER BY md5(id || ':va:42') LIMIT {m}"


@query("bfs_cost_vs_h", f"WITH {o.graph('order_part')}, rr AS ({_va_sql(50)}), {o.roots(3, 'rr')} " + " UNION ALL ".join(f"SELECT {h} AS h, (SELECT count(*) FROM b{h}) AS nodes_met, (SELECT count(*) FROM b{h - 1} JOIN adj ON u = node) AS arcs_read" for h in (1, 2, 3)))
def _bfs_cost(s, d):
    """Nodes met and arcs read by the searches from 50 random roots, for each radius."""
    g = graph(s, d, "order_part")
    roots = g.nodes.orderBy(key(F.col("id"), F.lit("va"))).limit(50).select(F.col("id").alias("root"))
    deg = g.adj.groupBy(F.col("u").alias("node")).agg(F.count(F.lit(1)).alias("deg"))
    reach = balls(g.adj, roots, 3).join(deg, "node", "left")
    at = reach.groupBy("dist").agg(F.count(F.lit(1)).alias("met"), F.sum("deg").alias("arcs"))
    hs = s.range(1, 4).select(F.col("id").cast("int").alias("h"))
    up = hs.join(at, F.col("dist") <= F.col("h"))
    return up.groupBy("h").agg(F.sum("met").alias("nodes_met"), F.coalesce(F.sum(F.when(F.col("dist") < F.col("h"), F.col("arcs"))), F.lit(0)).alias("arcs_read"))


def _m_sql(m: int, h: int) -> str:
    return f"SELECT {m} AS m, {h} AS h, count(*) AS population, (SELECT count(*) FROM b{h}) AS ball_rows FROM s{h}"


@query("sampling_cost_vs_m", " UNION ALL ".join(f"SELECT * FROM (WITH {o.graph('order_part')}, va AS MATERIALIZED ({_va_sql(m)}), {o.seeds(3, 'va')}, {o.roots(3, 'va')} " + " UNION ALL ".join(_m_sql(m, h) for h in (1, 2, 3)) + ")" for m in SIZES))
def _sampling_cost(s, d):
    """Population that one search over ``m`` event nodes meets, and the ball rows that separate searches would."""
    g = graph(s, d, "order_part")
    out = []
    for m in SIZES:
        va = cut(g.nodes.orderBy(key(F.col("id"), F.lit("va"))).limit(m).select(F.col("id").alias("node")))
        pop, rows = (x.groupBy("dist").agg(F.count(F.lit(1)).alias(n)) for x, n in ((set_ball(g.adj, va, 3), "population"), (balls(g.adj, va.select(F.col("node").alias("root")), 3), "ball_rows")))
        both = pop.join(rows, "dist", "full").na.fill(0)
        hs = s.range(1, 4).select(F.col("id").cast("int").alias("h"))
        out.append(hs.join(both, F.col("dist") <= F.col("h")).groupBy(F.lit(m).alias("m"), "h").agg(F.sum("population").alias("population"), F.sum("ball_rows").alias("ball_rows")))
    return _union(out)


_z = "SELECT {n} AS n, (SELECT count(*) FROM (SELECT DISTINCT cnt_a / size, cnt_b / size FROM (SELECT * FROM dens ORDER BY md5(node || ':42'), node LIMIT {n}))) AS cells"


@query("z_cost_vs_n", f"{o.dens(COP, A, B, 1)} " + " UNION ALL ".join(_z.format(n=n) for n in (100, 300, 1000)))
def _z_cost(s, d):
    """Distinct density pairs among ``n`` references: votes run over pairs of these, not of references."""
    g = graph(s, d)
    dens = cut(Pair(g, A, B).densities())
    return _union([kendall.cells(dens.orderBy(key(F.col("node")), "node").limit(n)).agg(F.lit(n).alias("n"), F.count(F.lit(1)).alias("cells")) for n in (100, 300, 1000)])


# streams, stores and sets
@query("late_events", "SELECT count(*) AS n, count(*) FILTER (WHERE ts < top - INTERVAL 1 HOUR) AS late FROM (SELECT ts, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM events)")
def _late(s, d):
    """Rows that come, in id order, over an hour behind the latest time before them: what a watermark of an hour would drop row by row.

    Running maxima run within blocks of ids; one row a block carries the maximum on."""
    ev = graphs.read(s, d, "events", "event_id", "ts").withColumn("block", F.expr("event_id div 100000"))
    before = ev.groupBy("block").agg(F.max("ts").alias("m")).withColumn("m", F.max("m").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)))
    own = F.max("ts").over(Window.partitionBy("block").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    top = ev.withColumn("own", own).join(before, "block").withColumn("top", F.greatest("own", "m"))
    return top.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("ts") < F.col("top") - F.expr("INTERVAL 1 HOUR")).alias("late"))


@query("index_roundtrip", f"WITH {o.graph(COP)}, nn AS (SELECT id AS node FROM nodes), {o.roots(2, 'nn')} SELECT 2 AS h, count(*) AS n, sum(size)::BIGINT AS total FROM (SELECT count(*) AS size FROM b2 GROUP BY root)")
def _index(s, d):
    """Sizes for two radii, stored by radius and read back for one: the scan opens that folder alone."""
    g = graph(s, d)
    at = f"{s.sparkContext.getCheckpointDir()}/vsize_{uuid.uuid4().hex}"
    index.vicinity_sizes(g, 1).unionByName(index.vicinity_sizes(g, 2)).repartition("h").write.partitionBy("h").parquet(at)
    return s.read.schema("node long, size long, h int").parquet(at).where("h = 2").groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("total"))


query("cosine_knn", f"WITH {o.graph('embed_knn')} SELECT src, dst FROM edges")(lambda s, d: graph(s, d, "embed_knn").edges)
query("set_except_vicinity", f"WITH {o.graph(COP)}, {o.events(A, B)}, {o.seeds(1)} SELECT id AS node FROM nodes EXCEPT SELECT node FROM s1")(lambda s, d: (g := graph(s, d)).nodes.select(F.col("id").alias("node")).exceptAll(kendall.reference_population(g, A, B, 1).select("node")).distinct())
Q["graph_copurchase"], SQL["graph_copurchase"] = Q[f"graph_{COP}"], SQL[f"graph_{COP}"]
query("fluent_test", f"SELECT '{A}' AS a, '{B}' AS b, 2 AS h, n, s, z, verdict FROM ({o.exact(COP, A, B, 2)})")(lambda s, d: Pair(graph(s, d), A, B).radius(2).test().select("a", "b", "h", "n", "s", F.round("z", 6).alias("z"), "verdict"))
query("fluent_importance")(lambda s, d: Pair(graph(s, d), "Brand#4", "Brand#2").radius(2).sample(300, "importance").test())
