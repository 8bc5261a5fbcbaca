"""Two-hop balls by blocks, against brute force."""

import numpy as np
import pytest

from vicicorr.operators import blocks, kendall
from vicicorr.operators.skeleton import ball_counts
from vicicorr.sources import graphs


@pytest.mark.parametrize("leaves", [0, 40])
def test_two_hop_balls_match_brute_force(spark, monkeypatch, leaves):
    """Several blocks, a hub, far ids, roots without an edge; with leaves on the skeleton, without them on the graph."""
    monkeypatch.setattr(blocks, "NODES", 20)
    monkeypatch.setattr(blocks, "BITMAP", 200)
    monkeypatch.setattr(blocks, "PATHS", 50)
    rng = np.random.default_rng(3)
    name = lambda i: int(i) * 10**15 - 5 * 10**16
    pairs = [(name(i), name(j)) for i, j in rng.integers(0, 100, (150, 2))] + [(name(0), name(j)) for j in range(1, 60)] + [(name(j), name((j + 1) % 100)) for j in range(100)]
    pairs += [(name(i % 100), name(200 + i)) for i in range(leaves)]
    occ = [(name(i), e) for i in range(0, 100, 3) for e in "ab" if rng.random() < 0.6] + [(name(500), "a")]
    g = graphs.from_edges(spark.createDataFrame(pairs, "x long, y long"), spark.createDataFrame(occ, "node long, event string"))
    near = {}
    for x, y in pairs:
        near.setdefault(x, {x}).add(y)
        near.setdefault(y, {y}).add(x)
    near[name(500)] = {name(500)}
    a, b = ({n for n, e in occ if e == k} for k in "ab")
    want = {}
    for r in near:
        ball = set().union(*(near[v] for v in near[r]))
        want[r] = (len(ball), len(ball & a), len(ball & b), len(ball & (a | b)))
    got = ball_counts(g, g.nodes.toDF("root"), g.event_nodes("a", "b").toDF("node", "cnt_a", "cnt_b"), 2).collect()
    assert len(got) == len(want) and {r.root: (r["size"], r.cnt_a, r.cnt_b, r.c) for r in got} == want
    assert "packed" in g.kept["skeleton"].kept  # by blocks, not by a row a (block of 62 roots, node)


def test_coded_numbers_come_back():
    x = np.array([5, -(2**63), 2**63 - 1, 0, 0, 7])
    assert (blocks.decoded(blocks.coded(x)) == x).all() and not len(blocks.decoded(blocks.coded(x[:0])))


def test_long_blocks_match_pairs():
    rng = np.random.default_rng(2)
    a, b = rng.integers(0, 90, 700) / 7, rng.integers(0, 70, 700) / 3
    assert kendall.block_sum(a, b) == int(sum(np.sign(a[i] - a[i + 1 :]) @ np.sign(b[i] - b[i + 1 :]) for i in range(700)))
