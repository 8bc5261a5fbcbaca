"""Choice of a sampler from index statistics."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.index import vicinity_sizes
from ..sources.graphs import EventGraph


@dataclass(frozen=True)
class SamplerPlan:
    sampler: str
    h: int
    m: int
    n_sum: int
    n_hat: float
    p_succ: float
    cost_enumerate: float
    cost_rejection: float
    cost_importance: float
    cost_whole_graph: float


def graph_stats(g: EventGraph) -> DataFrame:
    e = g.edges.agg(F.count(F.lit(1)).alias("n_edges"))
    d = g.adj.groupBy("u").count().agg(F.max("count").alias("max_degree"), F.sum("count").alias("ends"))
    return g.nodes.agg(F.count(F.lit(1)).alias("n_nodes")).crossJoin(e).crossJoin(d).select("n_nodes", "n_edges", "max_degree", (F.col("ends") / F.col("n_nodes")).alias("mean_degree"))


def choose_sampler(g: EventGraph, a: str, b: str, h: int, n: int = 900) -> SamplerPlan:
    """Costs in rows touched; the population is estimated from ball sizes, without a search."""
    st = graph_stats(g).first()
    own = vicinity_sizes(g, h, g.event_nodes(a, b).select("node")).agg(F.count(F.lit(1)), F.coalesce(F.sum("size"), F.lit(0))).first()
    m, n_sum, nodes = own[0], own[1], st.n_nodes
    n_hat = max(1.0, min(n_sum, nodes * (1 - math.exp(-n_sum / max(nodes, 1)))))
    ball = n_sum / max(m, 1) * (1 + st.mean_degree)
    p = n_hat / max(n_sum, 1)
    cost = {"enumerate": n_hat * (1 + st.mean_degree), "rejection": 2 * n / max(p, 1e-9) * ball, "importance": n * ball, "whole_graph": max(0.0, n * nodes / n_hat - n) * ball}
    # one hop: importance; else the cheapest, rejection only where its draws are seldom refused
    best = "importance" if h == 1 else min(("enumerate", "importance", "whole_graph", *(("rejection",) if p > 0.9 else ())), key=cost.get)
    return SamplerPlan(best, h, m, n_sum, n_hat, p, cost["enumerate"], cost["rejection"], cost["importance"], cost["whole_graph"])


def plan_frame(g: EventGraph, a: str, b: str, hs=(0, 1, 2, 3)) -> DataFrame:
    rows = [tuple(asdict(choose_sampler(g, a, b, h)).values()) for h in hs]
    return g.nodes.sparkSession.createDataFrame(rows, "sampler string, h int, m long, n_sum long, n_hat double, p_succ double, cost_enumerate double, cost_rejection double, cost_importance double, cost_whole_graph double")
