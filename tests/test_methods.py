"""Samplers to the end of a population, the reweighted test, masks, planted pairs, patterns, streams and the call surface, against brute force."""

import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from vicicorr.api import Pair
from vicicorr.functions import stats, udfs
from vicicorr.operators import balls, baselines, index, kendall, samplers, screen, simulate
from vicicorr.plans import costs, planner
from vicicorr.sources import graphs
from vicicorr.streaming import occurrences


def make(spark, pairs, occ):
    return graphs.from_edges(spark.createDataFrame(pairs, "x long, y long"), spark.createDataFrame(occ, "node long, event string"))


@pytest.fixture(scope="module")
def clique(spark):
    occ = [(i, "a") for i in range(20)] + [(i, "b") for i in range(20, 40)]
    return make(spark, list(itertools.combinations(range(40), 2)), occ).stored()


@pytest.fixture(scope="module")
def small():
    rng = random.Random(5)
    pairs = sorted({tuple(sorted(rng.sample(range(60), 2))) for _ in range(90)})
    occ = [(i, e) for i in range(60) for e in "abc" if rng.random() < 0.25]
    near = {i: {i} for i in range(60)}
    for x, y in pairs:
        near[x].add(y)
        near[y].add(x)
    return pairs, occ, near


def ball(near, root, h):
    seen = {root}
    for _ in range(h):
        seen = set().union(*(near[x] for x in seen))
    return seen


@pytest.mark.parametrize(("n", "accept", "want"), [(30, True, 30), (40, False, 40), (50, False, 40)])
def test_draws_go_on_until_all_are_there(clique, n, accept, want):
    r = samplers.draw_rounds(clique, "a", "b", 1, n, accept=accept)
    got = [x.node for x in r.refs.collect()]
    assert len(got) == len(set(got)) == r.n_got == want and r.exhausted == (n > 40)


def test_distinct_members_of_a_ball(clique):
    drawn = clique.nodes.sparkSession.createDataFrame([(1, 3, 40, 39), (2, 5, 40, 0)], "j long, root long, size long, at long")
    rows = samplers.members(clique, drawn, 1, k=50, distinct_within=True).collect()
    assert all(len({r.node for r in rows if r.j == j}) == 40 == sum(r.j == j for r in rows) for j in (1, 2))


@pytest.mark.parametrize("h", [0, 1, 2, 3])
def test_densities_by_brute_force(spark, small, h):
    pairs, occ, near = small
    g = make(spark, pairs, occ)
    flags = {e: {i for i, x in occ if x == e} for e in "ab"}
    for r in kendall.densities(g, kendall.reference_population(g, "a", "b", h), "a", "b", h).collect():
        b = ball(near, r.node, h)
        assert (r.size, r.cnt_a, r.cnt_b, r.c) == (len(b), len(b & flags["a"]), len(b & flags["b"]), len(b & (flags["a"] | flags["b"])))
    hits = {r.node for r in balls.hits_within(g.adj, g.nodes.select(F.col("id").alias("node")), g.event_nodes("a", "b"), h).collect()}
    assert hits == {i for i in near if ball(near, i, h) & (flags["a"] | flags["b"])} & {r.id for r in g.nodes.collect()}
    pop = {r.node for r in samplers.SAMPLERS["whole_graph"](g, "a", "b", h, 1000, first=4).collect()}
    assert pop == hits


def test_masks_of_many_blocks(spark, small):
    pairs, occ, near = small
    g = make(spark, pairs, occ)
    got = {r.number: r.root for r in balls.numbered_roots(g.nodes.select(F.col("id").alias("root")), block=7).collect()}
    assert sorted(got.values()) == sorted(r.id for r in g.nodes.collect())


def test_block_sum_and_inversions():
    rng = np.random.default_rng(4)
    for n in (0, 1, 2, 7, 64, 301):
        a, b = rng.integers(0, 6, n), rng.integers(0, 9, n)
        assert kendall.block_sum(a, b) == sum(int(np.sign(a[i] - a[i + 1 :]) @ np.sign(b[i] - b[i + 1 :])) for i in range(n))
        assert kendall.inversions(b) == sum(int((b[i] > b[i + 1 :]).sum()) for i in range(n))


def test_grid_beyond_the_bound(spark, sf, monkeypatch):
    g = graphs.stored_graph(spark, sf, "copurchase_part")
    assert graphs.stored_graph(spark, sf, "copurchase_part") is g
    monkeypatch.setattr(kendall, "PAIRS_UP_TO", 10)
    r = kendall.exact_test(g, "SMALL", "LARGE", 2).first()
    assert (r.n, r.s) == (1853, -359700) and r.z == pytest.approx(-13.54071, abs=1e-4)


def test_reweighted_test(spark):
    rng = random.Random(3)
    rows = [(i, rng.randrange(1, 4), 10, rng.randrange(5), rng.randrange(5), rng.randrange(1, 6)) for i in range(60)]
    r = kendall.weighted_test(spark.createDataFrame(rows, "node long, w long, size long, cnt_a long, cnt_b long, c long")).first()
    up = down = 0.0
    for x, y in itertools.combinations(rows, 2):
        o = x[1] / x[5] * y[1] / y[5]
        up += o * np.sign(x[3] - y[3]) * np.sign(x[4] - y[4])
        down += o
    plain = kendall.kendall_test(spark.createDataFrame(rows, "node long, w long, size long, cnt_a long, cnt_b long, c long")).first()
    assert r.t == pytest.approx(up / down) and r.z == pytest.approx(r.t * (60 * 59 / 2) / math.sqrt(plain.var_s))
    even = kendall.weighted_test(spark.createDataFrame([(i, 2, 10, a, b, 2) for i, _, _, a, b, _ in rows], "node long, w long, size long, cnt_a long, cnt_b long, c long")).first()
    assert even.z == pytest.approx(plain.z)


@pytest.mark.parametrize("h", [0, 3])
def test_auto_plans_any_radius(spark, small, h):
    g = make(spark, small[0], small[1])
    assert Pair(g, "a", "b").radius(h).sample(15, "auto").test().first().n == 15
    assert {r.h for r in planner.plan_frame(g, "a", "b").collect()} == {0, 1, 2, 3}


def test_planted_pairs_keep_their_distances(spark, sf):
    g = graphs.stored_graph(spark, sf, "copurchase_part")
    for positive in (True, False):
        rows = simulate.planted_pairs(g, 2, 20, [1, 2, 3], positive).collect()
        for p in (1, 2, 3):
            a, b = ({r.node for r in rows if r.pair == p and r.event == e} for e in "ab")
            near = {r.node for r in balls.set_ball(g.adj, spark.createDataFrame([(x,) for x in a], "node long"), 2).collect()}
            assert len(a) == 20 and (b <= near if positive else not b & near) and b
    noisy = simulate.noisy_pairs(g, simulate.planted_pairs(g, 2, 20, [1], False), 2, [0.0, 1.0], False).collect()
    at = {(x, e): {r.node for r in noisy if r.noise == x and r.event == e} for x in (0.0, 1.0) for e in "ab"}
    assert at[1.0, "b"] <= at[1.0, "a"] and not at[0.0, "b"] & at[0.0, "a"]
    whole = simulate.noisy_pairs(g, simulate.planted_pairs(g, 2, 20, [1], True), 2, [0.0], True).collect()
    assert sum(r.event == "b" for r in whole) == sum(r.event == "b" for r in simulate.planted_pairs(g, 2, 20, [1], True).collect())


def test_recall_grid_agrees_with_single_tests(spark, sf):
    g = graphs.stored_graph(spark, sf, "copurchase_part")
    many = {(r.positive, r.h): r for r in simulate.recall_grid(g, (2, 3), 60, 5000, 2).collect()}
    for positive in (True, False):
        z = [simulate.detect(g, (simulate.planted_positive if positive else simulate.planted_negative)(g, 3, 60, seed=p), 3, 5000).first().z for p in (100, 101)]
        assert many[positive, 3].mean_z == pytest.approx(np.mean(z)) and many[positive, 3].recall == 1.0
    rate = simulate.error_rates(g, (1,), 20, 300, 4).first()
    assert rate.pairs == 4 and 0 <= rate.upper <= 1


def test_edge_edits(spark, sf):
    g = graphs.stored_graph(spark, sf, "copurchase_part")
    n = g.edges.count()
    more, fewer = (simulate.edit_edges(g, p).edges for p in (50, -50))
    assert n * 1.45 < more.count() <= n * 1.5 and more.where("src >= dst").count() == 0 and g.edges.exceptAll(more).count() == 0
    assert abs(fewer.count() / n - 0.5) < 0.05
    ids = simulate.indexed(g.nodes).agg(F.min("i"), F.max("i"), F.count_distinct("i")).first()
    assert tuple(ids) == (0, g.nodes.count() - 1, g.nodes.count())


def test_pattern_sets_by_brute_force(spark, small):
    pairs, occ, near = small
    g = make(spark, pairs, occ)
    nodes = [r.id for r in g.nodes.collect()]
    reach = {}
    for e in "abc":
        own = {i for i, x in occ if x == e}
        reach[e] = {i: next((math.exp(-h) for h in range(3) if ball(near, i, h) & own), 0.0) for i in nodes}
    want = {}
    for k in (2, 3):
        for items in itertools.combinations("abc", k):
            total = sum(math.prod(reach[e][i] for e in items) for i in nodes)
            if total >= 1:
                want["|".join(items)] = total / len(nodes)
    got = {r["items"]: r.support for r in baselines.proximity_sets(g, least=1.0).collect()}
    assert got == pytest.approx(want) and any(k.count("|") == 2 for k in want)


def test_screen_and_index(spark, small):
    pairs, occ, near = small
    g = make(spark, pairs, occ)
    n = g.nodes.count()
    for r in screen.screen(g, n, 1, least=1).collect():
        own = kendall.exact_test(g, r.a, r.b, 1).first()
        assert (r.n, r.s) == (own.n, own.s)
    assert all(r["size"] == len(ball(near, r.node, 2)) for r in index.vicinity_sizes(g, 2).collect())
    for r in index.sketched_sizes(g, 2).collect():
        assert abs(r["size"] - len(ball(near, r.node, 2))) <= 2


def test_baselines_by_brute_force(spark, small):
    pairs, occ, near = small
    g = make(spark, pairs, occ)
    nodes = [r.id for r in g.nodes.collect()]
    p = {3: {3: 1.0}}
    mass = {3: 1.0}
    for _ in range(4):
        step = {3: 0.15}
        for u, x in mass.items():
            out = near[u] - {u}
            for v in out:
                step[v] = step.get(v, 0) + 0.85 * x / len(out)
        mass = step
    got = {r.node: r.p for r in baselines.personal_pagerank(g, spark.createDataFrame([(3,)], "root long")).collect()}
    assert got == pytest.approx(mass) and p
    trials = {r.trial: r.proximity for r in baselines.self_correlation(g, "a", trials=2).collect()}
    assert set(trials) == {0, 1, 2} and all(0 <= x <= 1 for x in trials.values())
    null = baselines.distance_permutation(g, "a", "b", rounds=10).first()
    own = {e: {i for i, x in occ if x == e} for e in "ab"}
    dist = lambda i: next((h for h in range(4) if ball(near, i, h) & own["b"]), 4)
    assert null.observed == pytest.approx(np.mean([dist(i) for i in own["a"]])) and 0 < null.p_low <= 1
    coords = {r.node: r.coords for r in baselines.landmark_coordinates(g, k=3).collect()}
    marks = [n for n in nodes if 0 in coords[n]]
    assert len(marks) == 3
    refs = spark.createDataFrame([(i,) for i in nodes[:5]], "node long")
    for r in baselines.landmark_densities(g, refs, "a", "b", k=3).collect():
        assert r.da == pytest.approx(sum(math.exp(-math.dist(coords[r.node], coords[i])) for i in own["a"]))
    assert baselines.embedding_test(g, g.nodes.select(F.col("id").alias("node")), "a", "b").first().n == len(nodes)


def test_formulas_and_user_functions(spark):
    r = spark.range(1).select(stats.var_no_ties(F.lit(30.0)).alias("v"), stats.var_bound(F.lit(900), F.lit(0.3)).alias("b"), stats.two_sided(F.lit(-1.96)).alias("p"), udfs.normal_sf(F.lit(1.96)).alias("q")).first()
    assert r.v == pytest.approx(2 * 65 / (9 * 30 * 29)) and r.b == pytest.approx(2 * 0.91 / 900)
    assert r.p == pytest.approx(0.05, abs=1e-4) and r.q == pytest.approx(0.025, abs=1e-4)
    assert stats.required_n(0.0, 0.05) == 800


def test_costs_are_read(spark):
    c = costs.run_cost(spark, lambda: spark.range(100_000).groupBy(F.col("id") % 7).count().collect())
    assert c.stages >= 2 and c.shuffle_bytes > 0


def test_closed_windows_equal_the_batch(spark, sf):
    g = graphs.stored_graph(spark, sf, "user_handoff")
    stream = occurrences.occurrence_stream(spark, sf)
    got = {r.start: (r.n, r.s) for r in occurrences.test_windows(stream, g, "error", "purchase", 1).collect()}
    ev = spark.read.parquet(f"{sf}/events.parquet").select(F.col("user_id").alias("node"), F.col("event_type").alias("event"), F.col("ts").cast("timestamp").alias("ts"))
    top = ev.agg(F.max("ts") - F.expr("INTERVAL 1 HOUR")).first()[0]
    days = occurrences.window_nodes(ev, "error", "purchase").where(F.col("start") + F.expr("INTERVAL 1 DAY") <= F.lit(top))
    assert got == {r.start: (r.n, r.s) for r in occurrences.test_nodes(days, g, 1).collect()} and got


@pytest.mark.parametrize("h", [2, 3])
def test_skeleton_by_brute_force(spark, h):
    """Trees that hang on a core, twins with different events, two-node and lone nodes, a cycle of twins."""
    from vicicorr.operators.skeleton import skeleton

    rng = np.random.default_rng(5)
    pairs = {(int(x), int(y)) for x, y in rng.integers(0, 12, (14, 2)) if x != y}  # a core
    pairs |= {(100 + i, x) for i in range(12) for x in (1, 4, 7)} | {(120 + i, x) for i in range(5) for x in (100, 3)}  # twins
    pairs |= {(i, int(rng.integers(200, i)) if i > 205 else int(rng.integers(0, 12))) for i in range(200, 240)} | {(240 + i, 239) for i in range(6)}  # trees
    pairs |= {(300, 301), (310, 311), (311, 312), (310, 313), (312, 313)} | {(400, x) for x in range(401, 407)}
    ids = sorted({x for p in pairs for x in p} | {500, 501})
    occ = [(i, e) for i in ids for e in "ab" if rng.random() < 0.4] + [(500, "a")]
    g = graphs.from_edges(spark.createDataFrame(sorted(pairs), "x long, y long"), spark.createDataFrame(occ, "node long, event string"), spark.createDataFrame([(i,) for i in ids], "id long"))
    near = {i: {i} for i in ids}
    for x, y in pairs:
        near[x].add(y)
        near[y].add(x)
    has = {e: {i for i, k in occ if k == e} for e in "ab"}
    want = set()
    for i in ids:
        ball = {i}
        for _ in range(h):
            ball = set().union(*(near[x] for x in ball))
        want.add((i, len(ball), len(ball & has["a"]), len(ball & has["b"]), len(ball & (has["a"] | has["b"]))))
    got = kendall.densities(g, g.nodes.select(F.col("id").alias("node")), "a", "b", h)
    assert {(r.node, r["size"], r.cnt_a, r.cnt_b, r.c) for r in got.collect()} == want
    sk = skeleton(g)
    assert sk.levels > 1 and sk.twins.count() >= 11 and skeleton(g.with_occ(g.occ)) is sk
    some = [i for i in ids if i % 3 == 0]
    got = kendall.densities(g, spark.createDataFrame([(i,) for i in some], "node long"), "a", "b", h)
    assert {(r.node, r["size"], r.cnt_a, r.cnt_b, r.c) for r in got.collect()} == {w for w in want if w[0] in some}


def test_concordance_keeps_every_pair(spark, sf):
    """Members and pairs of classes give back each pair's vote; equal densities take one row a reference."""
    from vicicorr import queries as q

    rows = q.Q["concordance_pairs"](spark, sf).collect()
    rep = {r.i: r.j for r in rows if r.kind == "member"}
    votes = {(r.i, r.j): r.vote for r in rows if r.kind == "pair"}
    dens = {r.node: (r.cnt_a, r.cnt_b) for r in q._dens(spark, sf, 0, "copurchase_part", "Brand#4", "Brand#2").collect()}
    assert set(rep) == set(dens) and len(votes) < len(dens)
    for i, j in itertools.combinations(sorted(dens), 2):
        (a1, b1), (a2, b2) = dens[i], dens[j]  # at no hops sizes are one
        want = int(np.sign(a1 - a2) * np.sign(b1 - b2))
        assert want == (0 if rep[i] == rep[j] else votes[min(rep[i], rep[j]), max(rep[i], rep[j])])


@pytest.mark.parametrize(("name", "table", "rows"), [("p_value", "lineitem", 100), ("p_two_sided", "lineitem", 100), ("required_n", "lineitem", 100), ("fig3_inflation", "orders", 2)])
def test_worked_queries_read_a_table(spark, sf, tmp_path, name, table, rows):
    """They follow the table they are given: of half of it they give other values."""
    from vicicorr import queries as q

    assert len(whole := q.Q[name](spark, sf).collect()) == rows
    key = {"lineitem": "l_orderkey", "orders": "o_orderkey"}[table]
    graphs.read(spark, sf, table).where(f"{key} % 2 = 0").write.parquet(f"{tmp_path}/{table}.parquet")
    assert q.Q[name](spark, str(tmp_path)).collect() != whole


def test_out_of_sight_parts_move_z_up(spark, sf):
    from vicicorr import queries as q

    z = {r.refs: (r.n, r.z) for r in q.Q["out_of_sight_inflation"](spark, sf).collect()}
    assert z["all"][0] > z["in sight"][0] and z["all"][1] > z["in sight"][1]


def test_scans_read_every_column(spark, sf):
    from vicicorr import queries as q

    for t in ("benchmark", "customer", "labels"):
        df = q.Q[f"scan_{t}"](spark, sf)
        assert df.first().n == graphs.read(spark, sf, t).count()
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert all(c in plan.split("ReadSchema: ")[1] for c in graphs.read(spark, sf, t).columns)
