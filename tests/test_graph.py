"""Golden values, worked toys and brute force for the graph test."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vicicorr.operators import baselines, kendall, samplers
from vicicorr.operators.balls import set_ball
from vicicorr.sources import graphs


@pytest.mark.parametrize(
    ("name", "a", "b", "h", "n", "s", "z"),
    [
        ("copurchase_part", "SMALL", "LARGE", 1, 1531, -460993, -24.05664),
        ("copurchase_part", "Brand#4", "Brand#2", 1, 706, -116486, -20.56701),
        ("page_path", "en", "fr", 1, 487, 13581, 4.25296),
        ("doc_shingle", "q1", "t1", 1, 880, 40288, 4.80546),
        ("user_handoff", "error", "purchase", 1, 135, -1733, -3.38035),
    ],
)
def test_golden(spark, sf, name, a, b, h, n, s, z):
    r = kendall.exact_test(graphs.BUILDERS[name](spark, sf), a, b, h).first()
    assert (r.n, r.s) == (n, s)
    assert r.z == pytest.approx(z, abs=1e-4)


def path(spark, n, a, b):
    pairs = spark.createDataFrame([(i, i + 1) for i in range(n - 1)], "x long, y long")
    occ = spark.createDataFrame([(i, "a") for i in a] + [(i, "b") for i in b], "node long, event string")
    return graphs.from_edges(pairs, occ)


def test_path_ball(spark):
    g = path(spark, 7, [3], [])
    assert sorted(r.node for r in set_ball(g.adj, g.occ, 2).collect()) == [1, 2, 3, 4, 5]


def test_constant_density_has_no_z(spark):
    r = kendall.exact_test(path(spark, 5, [2], []), "a", "b", 1).first()
    assert r.z is None and r.verdict == "undetermined"


def test_grid_and_blocks_match_pairs(spark):
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 9, 300), rng.integers(0, 7, 300)
    want = int(sum(np.sign(a[i] - a[i + 1 :]) @ np.sign(b[i] - b[i + 1 :]) for i in range(300)))
    assert kendall.block_sum(a, b) == want
    dens = spark.createDataFrame([(i, 1, int(x), int(y)) for i, (x, y) in enumerate(zip(a, b, strict=True))], "node long, size long, cnt_a long, cnt_b long")
    assert kendall.kendall_s_grid(dens, 8).first().s == want
    p = kendall.pair_counts(dens).first()
    assert p.concordant - p.discordant == want


def test_samplers_stay_in_population(spark, sf):
    g = graphs.copurchase_part(spark, sf)
    pop = {r.node for r in kendall.reference_population(g, "Brand#4", "Brand#2", 1).collect()}
    for f in samplers.SAMPLERS.values():
        got = [r.node for r in f(g, "Brand#4", "Brand#2", 1, 50).collect()]
        assert len(got) == len(set(got)) == 50 and set(got) <= pop


def test_transaction_correlation(spark, sf):
    r = baselines.transaction_measures(graphs.doc_shingle(spark, sf), "q0", "t1").first()
    assert (r.s, r.n11) == (6042, 9)
    assert r.z == pytest.approx(3.71369, abs=1e-4) and r.lift == pytest.approx(3.04260, abs=1e-4)


def test_upper_tail(spark):
    from vicicorr.functions.stats import upper_p

    assert spark.range(1).select(upper_p(F.lit(2.33))).first()[0] == pytest.approx(0.0099, abs=1e-4)


def test_embed_knn_by_brute_force(spark, tmp_path):
    """Copies, parallel vectors and vectors without a direction, over several blocks."""
    rng = np.random.default_rng(3)
    some = rng.normal(size=(40, 6)).astype(np.float32)
    vec = [x.tolist() for x in np.r_[some, some[:9], np.repeat(some[:1], 20, 0), 2 * some[:5]]]
    odd = [[0.0] * 6, [float("nan")] + [1.0] * 5, [1.0, None] + [0.5] * 4, None]
    rows = [(i * 7 % 199, x, i % 2) for i, x in enumerate(vec + odd)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    fit = [(i, np.array(x, np.float64)) for i, x, _ in rows[: len(vec)]]
    want = set()
    for i, x in fit:
        near = sorted((-round(float(sum(p * q for p, q in zip(x, y, strict=True)) / (np.sqrt(x @ x) * np.sqrt(y @ y))), 10), j) for j, y in fit if j != i)
        want |= {(min(i, j), max(i, j)) for _, j in near[:5]}
    g = graphs.embed_knn(spark, str(tmp_path), block=16)
    assert {(r.src, r.dst) for r in g.edges.collect()} == want
    assert g.nodes.count() == len(rows)
