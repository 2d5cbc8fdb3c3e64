"""Hand-computed cases and published values."""

import math

import numpy as np
import pytest

from groupshift import kernels
from groupshift.functions import metrics, theory, tuning
from groupshift.operators import baselines, cusum, direction, locate, norms, relax, relops, scale, single
from groupshift.operators import groups as gr
from groupshift.sources import panels


def panel_of(spark, x):
    rows = [(i + 1, t + 1, float(v)) for i, row in enumerate(x) for t, v in enumerate(row)]
    return spark.createDataFrame(rows, panels.PANEL_SCHEMA)


def values(df, name):
    return {(r["series_id"], r["t"]): r[name] for r in df.collect()}


def test_cusum_values(spark):
    got = values(cusum.cusum(panel_of(spark, [[0, 1]])), "cusum")
    assert got == {(1, 1): pytest.approx(0.7071068)}
    got = values(cusum.cusum(panel_of(spark, [[0, 0, 1, 1], [5, 5, 5, 5]])), "cusum")
    assert [got[1, t] for t in (1, 2, 3)] == pytest.approx([0.5773503, 1, 0.5773503])
    assert [got[2, t] for t in (1, 2, 3)] == pytest.approx([0, 0, 0])
    assert cusum.cusum(panel_of(spark, [[3]])).count() == 0


def test_shrinkage_values(spark):
    c = spark.createDataFrame([(1, 1, 3.0), (2, 1, 4.0)], "series_id long, t long, cusum double")
    groups = gr.single(c)
    got = values(relax.block_shrink(c, groups, 1.0), "m")
    assert got[1, 1] / 3 == pytest.approx(0.7171573) and got[2, 1] / 4 == pytest.approx(0.7171573)
    got = values(relax.block_shrink(c, groups, 1.0, normalise=True), "m")
    assert (got[1, 1], got[2, 1]) == pytest.approx((0.6, 0.8))
    assert relax.block_shrink(c, groups, 4.0).count() == 0
    assert direction.leading_left(relax.columns_of(relax.block_shrink(c, groups, 4.0), "m")).count() == 0


def test_nothing_survives_gives_no_place(spark):
    x = np.zeros((4, 12))
    x[:, 6:] = 0.1
    found = single.detect_single(panel_of(spark, x), gr.blocks(spark, 4, 2, first=1), lam=50.0)
    assert tuple(found.point.first()) == (None, 0.0) and found.direction.count() == 0


@pytest.mark.parametrize(
    "setting, value",
    [((1000, 10, 100), 1.6070), ((1000, 10, 50), 1.8584), ((1000, 10, 200), 1.4292), ((1000, 19, 100), 1.6278), ((1000, 25, 20), 2.4231), ((1000, 25, 40), 2.0063), ((1200, 50, 10), 3.0978), ((1200, 100, 10), 3.1629)],
)
def test_levels(setting, value):
    assert tuning.lambda_theory(*setting) == pytest.approx(value, abs=5e-5)
    assert tuning.lambda_practical(*setting) == pytest.approx(value / 2, abs=5e-5)
    n, g, q = setting
    assert tuning.lambda_tail((n * g) ** -2.0, q) == pytest.approx(tuning.lambda_theory(n, g, q))


def test_more_levels():
    for (p, n), value in {(500, 1000): 2.0183, (1000, 1000): 2.1024, (2000, 1000): 2.1833, (500, 1200): 2.0215, (1000, 1200): 2.1055}.items():
        assert tuning.lambda_sparse(p, n) == pytest.approx(value, abs=5e-5)
    assert [round(m, 4) for m in tuning.GRID] == [0.1, 0.1763, 0.3107, 0.5477, 0.9655, 1.7019, 3.0]
    assert tuning.lambda_univariate(1000) == pytest.approx(1 + math.sqrt(4 * math.log(1000)))


def test_ari(spark):
    assert kernels.ari([2], [2], 4) == 1 and kernels.ari([2], [], 4) == 0
    truth = spark.createDataFrame([("a", 2), ("b", 2)], "config_id string, z long")
    found = spark.createDataFrame([("a", 2)], "config_id string, z long")
    assert {r.config_id: r.ari for r in metrics.ari(truth, found, 4).collect()} == {"a": 1.0, "b": 0.0}


def test_scales(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(0, [[1.0], [5.0], [0.0]], (3, 4000))
    x[:, 2000:] += 50  # a change hardly moves them
    for kind in ("mean_ad", "median_ad"):
        got = {r.series_id: r.sigma for r in scale.row_scale(panel_of(spark, x), kind).collect()}
        assert got[1] == pytest.approx(1, rel=0.05) and got[2] == pytest.approx(5, rel=0.05)
        assert [got[i + 1] for i in range(3)] == pytest.approx(list(kernels.row_scale(x, kind)))
    still = scale.standardised(panel_of(spark, [[7, 7, 7]]))
    assert {r.x for r in still.collect()} == {0.0}


def test_ties_go_to_the_earliest(spark):
    curve = spark.createDataFrame([(3, 2.0), (1, 2.0), (2, 1.0)], "t long, s double")
    assert tuple(locate.peak(curve, "s").first()) == (1, 2.0)
    assert tuple(locate.peak(curve.where("t > 9"), "s").first()) == (None, 0.0)


def test_groups(spark):
    w = gr.windows(spark, 1000, 100, 50)
    p = gr.profile(w).first()
    assert (p.g, p.p, p.least_size, p.overlap, p.disjoint) == (19, 1000, 100, 2, False)
    assert gr.profile(gr.windows(spark, 23, 10, 5)).first().p == 23
    b = gr.profile(gr.blocks(spark, 25, 10)).first()
    assert (b.g, b.least_size, b.disjoint, b.top_s) == (3, 5, True, 25)
    assert gr.components(w).select("component").distinct().count() == 1
    assert gr.components(gr.blocks(spark, 25, 10)).select("component").distinct().count() == 3


def test_panel_checks(spark):
    x = np.arange(6.0).reshape(2, 3)
    assert panels.check(panel_of(spark, x)) == {"p": 2, "n": 3}
    for bad in ("t <> 2 or series_id = 2", "t <> 1"):
        with pytest.raises(ValueError):
            panels.check(panel_of(spark, x).where(bad))


def test_segments(spark):
    x = np.array([[0.0] * 4 + [2.0] * 4, [1.0] * 8])
    changes = spark.createDataFrame([(4,)], "z long")
    means = {(r.series_id, r.segment): (r["mean"], r.n) for r in relops.segment_means(panel_of(spark, x), changes).collect()}
    assert means == {(1, 0): (0.0, 4), (1, 1): (2.0, 4), (2, 0): (1.0, 4), (2, 1): (1.0, 4)}
    jumps = relops.jump_vectors(panel_of(spark, x), changes).where("v <> 0").collect()
    assert [tuple(r) for r in jumps] == [(0, 1, 2.0)]
    found = norms.phi(relops.jump_vectors(panel_of(spark, x), changes), gr.blocks(spark, 2, 1, first=1)).collect()
    assert {r.group_id: r.norm for r in found} == {0: 2.0, 1: 0.0}


def test_theory_of_the_signal(spark):
    n, z = 60, 22
    x = np.zeros((2, n))
    x[0, z:], x[1, z:] = 3, 4
    profile = theory.signal_profile(n, z)
    got = values(cusum.cusum(panel_of(spark, x)), "cusum")
    assert [got[1, t] for t in range(1, n)] == pytest.approx([3 * g for g in profile])
    assert max(range(1, n), key=lambda t: profile[t - 1]) == z
    assert np.linalg.norm(kernels.cusum(x), 2) == pytest.approx(theory.operator_norm(n, z, 5))
    assert theory.operator_norm(n, z, 5) >= n * min(z, n - z) / n * 5 / 4
    assert tuple(baselines.l2(cusum.cusum(panel_of(spark, x))).first()) == (z, pytest.approx(theory.signal_peak(n, z, 5)))


def test_null_blocks_have_the_moments_of_chi_square():
    """A group's part of a change-free CUSUM column: its squared length has mean p_g and variance 2 p_g at every time."""
    rng = np.random.default_rng(12)
    for size in (1, 4, 12):
        squares = np.array([(kernels.cusum(rng.normal(size=(size, 30))) ** 2).sum(0) for _ in range(4000)])
        assert squares.mean(0) == pytest.approx(np.full(29, size), rel=0.12)
        assert squares.var(0) == pytest.approx(np.full(29, 2 * size), rel=0.25)
        assert squares.mean() == pytest.approx(size, rel=0.03) and squares.var() == pytest.approx(2 * size, rel=0.08)


def test_rank_one_form_has_the_optimum_of_the_direction():
    """Over rank-one matrices of unit nuclear norm with rows in s groups, the inner product with T is at most, and reaches, the length of v'T."""
    rng = np.random.default_rng(13)
    t, groups = rng.normal(size=(6, 9)), [np.array([0, 1]), np.array([2, 3]), np.array([4, 5])]
    for s in (1, 2, 3):
        v = kernels.best_group_subset(t, groups, s)
        best = np.linalg.norm(v @ t)
        m = np.outer(v, v @ t) / best
        assert np.linalg.norm(m, "nuc") == pytest.approx(1) and (m * t).sum() == pytest.approx(best)
        assert abs(kernels.leading_left(m) @ v) == pytest.approx(1)
        for _ in range(200):
            u, w = np.zeros(6), rng.normal(size=9)
            rows = np.concatenate([groups[g] for g in rng.choice(3, s, replace=False)])
            u[rows] = rng.normal(size=len(rows))
            other = np.outer(u, w)
            assert (other / np.linalg.norm(other, "nuc") * t).sum() <= best + 1e-9
