"""Solvers, directions and interval modes against each other, and the inequalities that hold for any input."""

import math
import re

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.functions import theory, tuning
from groupshift.operators import baselines, cusum, direction, intervals, locate, multi, norms, relax, single
from groupshift.operators import groups as gr
from groupshift.sources import panels


def panel_of(spark, x):
    rows = [(i + 1, t + 1, float(v)) for i, row in enumerate(x) for t, v in enumerate(row)]
    return spark.createDataFrame(rows, panels.PANEL_SCHEMA)


def matrix_of(df, p, n, name="m"):
    out = np.zeros((p, n))
    for r in df.collect():
        out[r["series_id"] - 1, r["t"] - 1] = r[name]
    return out


@pytest.fixture(scope="module")
def planted():
    groups = kernels.blocks(24, 4)
    theta = kernels.step_vector(24, groups, (1, 3), 2.5)
    return kernels.gaussian(24, 60, [(25, theta)], 4), groups, theta


def test_distributed_agrees_with_the_kernels(spark, planted):
    x, groups, _ = planted
    panel, bridge = panel_of(spark, x), gr.blocks(spark, 24, 4, first=1)
    c = kernels.cusum(x)
    assert matrix_of(cusum.cusum(panel), 24, 59, "cusum") == pytest.approx(c)
    assert matrix_of(cusum.cusum_blocked(panel, 7), 24, 59, "cusum") == pytest.approx(c)
    lam = tuning.lambda_practical(60, 6, 4)
    assert matrix_of(relax.block_shrink(cusum.cusum(panel), bridge, lam), 24, 59) == pytest.approx(kernels.block_shrink(c, groups, lam))
    columns = relax.columns_of(cusum.cusum(panel))
    w, over = gr.windows(spark, 24, 8, 4, first=1), kernels.windows(24, 8, 4)
    exact = matrix_of(relax.to_long(relax.columnwise_dual(columns, w, lam)), 24, 59)
    assert exact == pytest.approx(kernels.columnwise_dual(c, over, lam), abs=1e-7)
    steps = relax.conditional_gradient(columns.repartition(3), w, lam, eps=0, max_iter=12, save_every=5)
    assert matrix_of(relax.to_long(steps), 24, 59) == pytest.approx(kernels.conditional_gradient(c, over, lam, eps=0, most=12))
    z, stat, v = kernels.detect_single(x, groups, lam)
    found = single.detect_single(panel, bridge)
    assert tuple(found.point.first()) == (z, pytest.approx(stat))
    assert [r.v for r in found.direction.orderBy("series_id").collect()] == pytest.approx([a for a in v if a != 0], abs=1e-8)
    split = single.detect_single_split(panel, bridge, lam)
    assert tuple(split.point.first()) == (kernels.detect_split(x, groups, lam)[0], pytest.approx(kernels.detect_split(x, groups, lam)[1]))
    for name, run in {"l2": baselines.l2, "linf": baselines.linf, "double_cusum": baselines.double_cusum, "scan": baselines.scan}.items():
        assert tuple(run(cusum.cusum(panel)).first()) == pytest.approx(kernels.locate_by(c, name))
    assert tuple(baselines.sparse_projection(cusum.cusum(panel))[0].first()) == pytest.approx(kernels.sparse_projection(x)[:2])


def test_direction_methods_agree(spark, planted):
    x, groups, _ = planted
    columns = relax.columns_of(cusum.cusum(panel_of(spark, x)))
    want = kernels.leading_left(kernels.cusum(x))
    for method in ("gram", "power", "sketch"):
        got = [r.v for r in direction.leading_left(columns, method, steps=400).orderBy("series_id").collect()]
        assert got == pytest.approx(want, abs=1e-4), method


def test_projecting_data_first_is_the_same(spark, planted):
    x, _, theta = planted
    v = spark.createDataFrame([(i + 1, float(a)) for i, a in enumerate(theta)], "series_id long, v double")
    panel = panel_of(spark, x)
    a, b = locate.locate(v, cusum.cusum(panel)).first(), locate.locate(v, panel, on="data").first()
    assert a.z == b.z and a.stat == pytest.approx(b.stat)


def test_interval_modes_agree(spark, planted):
    x, _, _ = planted
    panel, bridge = panel_of(spark, x), gr.blocks(spark, 24, 4, first=1)
    some = intervals.draw_intervals(spark, 60, 15)
    got = {m: {r.q: r for r in multi.interval_candidates(panel, bridge, some, mode=m, steps=150).collect()} for m in ("replicated", "distributed")}
    for q, r in got["replicated"].items():
        other = got["distributed"][q]
        assert (r.s, r.e) == (other.s, other.e) and r.stat == pytest.approx(other.stat, rel=0.02)
    l2 = multi.interval_candidates(panel, bridge, some, 1.0, "l2", "distributed").collect()
    for r in l2:
        z, stat = kernels.locate_by(kernels.cusum(x[:, r.s : r.e]), "l2")
        assert (r.b, r.stat) == (r.s + z, pytest.approx(stat))


@pytest.mark.parametrize("stat", [*multi.DIRECTIONS, *multi.CURVES])
def test_distributed_has_the_same_detectors(spark, planted, stat):
    x, _, _ = planted
    panel = panel_of(spark, x)
    bridge = gr.blocks(spark, 24, 4, first=1) if stat == "gsp" else gr.windows(spark, 24, 8, 4, first=1)
    some = intervals.draw_intervals(spark, 60, 8)
    want, got = ({r.q: r for r in multi.interval_candidates(panel, bridge, some, 0.6, stat, mode).collect()} for mode in ("replicated", "distributed"))
    for q, r in want.items():
        assert (got[q].s, got[q].e, got[q].b) == (r.s, r.e, r.b) and got[q].stat == pytest.approx(r.stat, abs=1e-5)


def test_power_steps_converge_or_raise(spark, planted, monkeypatch):
    x, _, _ = planted
    panel, bridge = panel_of(spark, x), gr.blocks(spark, 24, 4, first=1)
    some = spark.createDataFrame([(0, 0, 60), (1, 5, 55)], "q int, s long, e long")
    want = {r.q: r.stat for r in multi.interval_candidates(panel, bridge, some, 0.6, mode="replicated").collect()}
    monkeypatch.setattr(multi, "LOCAL_CELLS", 0)
    got = {r.q: r.stat for r in multi.interval_candidates(panel, bridge, some, 0.6, mode="distributed").collect()}
    assert got == pytest.approx(want, abs=1e-4)
    with pytest.raises(RuntimeError):
        multi.interval_candidates(panel, bridge, some, 0.6, mode="distributed", steps=1)


@pytest.mark.parametrize("stat", ["gsp", "gsp_split", "unknown"])
def test_distributed_refuses_what_it_cannot_do(spark, planted, stat):
    panel, over = panel_of(spark, planted[0]), gr.windows(spark, 24, 8, 4, first=1)
    with pytest.raises(ValueError):
        multi.interval_candidates(panel, over, intervals.draw_intervals(spark, 60, 4), 0.6, stat, "distributed")


def test_intervals_are_uniform_and_valid(spark):
    rows = intervals.draw_intervals(spark, 12, 6000).collect()
    assert all(0 <= r.s and r.e - r.s >= 2 and r.e <= 12 for r in rows)
    counts = np.unique([(r.s, r.e) for r in rows], axis=0, return_counts=True)[1]
    assert len(counts) == 66 and counts.min() > 45 and counts.max() < 150


def test_recursion_stops(spark):
    rows = [(0, 0, 50, 20, 9.0), (1, 0, 20, 10, 3.0), (2, 20, 50, 35, 8.0), (3, 10, 30, 22, 99.0)]
    df = spark.createDataFrame(rows, multi.CANDIDATE)
    assert [r.z for r in multi.recurse(df, 50, 5.0).collect()] == [22]  # what crosses a found point is out
    assert [r.z for r in multi.recurse(df.where("q <> 3"), 50, 5.0).collect()] == [20, 35]
    assert multi.recurse(df, 50, 100.0).count() == 0 and multi.recurse(df.limit(0), 50, 1.0).count() == 0


def test_solvers_agree_for_disjoint_groups(planted):
    x, groups, _ = planted
    c = kernels.cusum(x)
    closed = kernels.block_shrink(c, groups, 1.0, normalise=True)
    exact = kernels.columnwise_dual(c, groups, 1.0)
    assert exact / np.linalg.norm(exact) == pytest.approx(closed, abs=1e-8)
    assert np.abs(kernels.conditional_gradient(c, groups, 1.0, eps=1e-9, most=400) - closed).max() < 2e-2


def test_iterative_solver_comes_near_the_exact_one(planted):
    x, _, _ = planted
    c, groups = kernels.cusum(x), kernels.windows(24, 8, 4)
    value = lambda m: float((c * m).sum()) - 0.7 * kernels.group_norm(m, groups)
    exact = kernels.columnwise_dual(c, groups, 0.7)
    best = value(exact / np.linalg.norm(exact))
    assert best == pytest.approx(np.linalg.norm(exact), rel=1e-6)
    assert value(kernels.conditional_gradient(c, groups, 0.7, eps=1e-6, most=300)) > best * 0.99


def test_relaxation_finds_what_the_ideal_problem_finds():
    groups = kernels.blocks(15, 3)
    theta = kernels.step_vector(15, groups, (2,), 4.0)
    c = kernels.cusum(kernels.gaussian(15, 80, [(30, theta)], 8))
    ideal, ours = kernels.best_group_subset(c, groups, 1), kernels.group_direction(c, groups, tuning.lambda_practical(80, 5, 3))
    assert abs(ideal @ ours) > 0.97 and set(np.flatnonzero(ideal)) == {6, 7, 8}


finite = st.floats(-50, 50)


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10**6), st.integers(2, 4), st.floats(0.01, 3))
def test_inequalities(seed, size, lam):
    rng = np.random.default_rng(seed)
    a, b = rng.normal(size=(2, 12, 9))
    over = kernels.windows(12, 2 * size, size)
    assert abs((a * b).sum()) <= kernels.group_norm(a, over) * kernels.dual_norm(b, over) + 1e-9
    most = max(np.bincount(np.concatenate(over)))
    assert kernels.group_norm(a, over) <= theory.norm_bound(int(most), 9, [len(g) for g in over], np.linalg.norm(a)) + 1e-9
    groups = kernels.blocks(12, size)
    m = kernels.block_shrink(a, groups, lam)
    value = lambda x: float((a * x).sum()) - lam * kernels.group_norm(x, groups)
    other = rng.normal(size=(12, 9))
    assert np.linalg.norm(m) >= value(other / np.linalg.norm(other)) - 1e-9
    if m.any():
        assert value(m / np.linalg.norm(m)) == pytest.approx(np.linalg.norm(m))
    single_rows = [np.array([i]) for i in range(12)]
    assert kernels.block_shrink(a, single_rows, lam) == pytest.approx(np.sign(a) * np.maximum(np.abs(a) - lam, 0))
    order = rng.permutation(12)
    back = np.argsort(order)
    moved = [back[g] for g in groups]
    assert kernels.block_shrink(a[order], moved, lam) == pytest.approx(m[order])
    t = kernels.cusum(2 * a + 3 * b + 7)
    assert t == pytest.approx(2 * kernels.cusum(a) + 3 * kernels.cusum(b))


def test_perturbation_bound():
    rng = np.random.default_rng(0)
    n, z, groups = 80, 32, kernels.blocks(20, 5)
    theta = kernels.step_vector(20, groups, (1,), 30.0)
    signal = kernels.cusum(np.repeat(theta[:, None], n, 1) * (np.arange(n) >= z))
    noise = rng.normal(size=signal.shape)
    lam = kernels.dual_norm(noise, groups)
    gap = theory.operator_norm(n, z, 30.0)
    m = kernels.block_shrink(signal + noise, groups, lam, normalise=True)
    u, _, w = np.linalg.svd(signal)
    distance, sine = theory.perturbation_bound(lam, 1, n, 5, gap)
    outer = np.outer(u[:, 0], w[0])
    assert min(np.linalg.norm(outer - m), np.linalg.norm(outer + m)) <= distance
    v = kernels.leading_left(m)
    assert math.sqrt(max(0, 1 - (v @ theta / 30) ** 2)) <= sine


def test_screening_is_safe():
    """A block no longer than its level is zero in the exact solution, overlapping groups included."""
    rng = np.random.default_rng(1)
    c, groups, lam = rng.normal(size=(24, 30)), kernels.windows(24, 8, 4), 0.9
    exact = kernels.columnwise_dual(c, groups, lam, tol=1e-12, sweeps=4000)
    for g in groups:
        short = np.sqrt((c[g] ** 2).sum(0)) <= lam * math.sqrt(len(g))
        assert np.abs(exact[np.ix_(g, np.flatnonzero(short))]).max(initial=0) < 1e-6


def test_norm_operators(spark, planted):
    x, groups, _ = planted
    c = kernels.cusum(x)
    df, bridge = cusum.cusum(panel_of(spark, x)), gr.blocks(spark, 24, 4, first=1)
    assert norms.group_norm(df, bridge).first()[0] == pytest.approx(kernels.group_norm(c, groups))
    assert norms.dual_norm(df, bridge).first()[0] == pytest.approx(kernels.dual_norm(c, groups))
    assert norms.frobenius(df).first()[0] == pytest.approx(np.linalg.norm(c))
    found = norms.spectral(relax.columns_of(df)).first()
    assert found.operator == pytest.approx(np.linalg.norm(c, 2)) and found.nuclear == pytest.approx(np.linalg.norm(c, "nuc"), rel=1e-5)


def test_many_series_go_by_the_gram_matrix_of_times(spark, sf, monkeypatch):
    """direction_gram, sin_theta, direction_lam0 and spectral_norms make no matrix of all series when these are many; the results stay."""
    from groupshift.operators import direction
    from groupshift.plans import registry

    names = ("direction_gram", "sin_theta", "direction_lam0", "spectral_norms")
    want = {n: sorted(map(tuple, registry.QUERIES[n](spark, sf).collect())) for n in names}

    def never(*_):
        raise MemoryError

    monkeypatch.setattr(direction, "GRAM_SERIES", 3)
    monkeypatch.setattr(direction, "SLICE_CELLS", 1)
    monkeypatch.setattr(direction, "_gram", never)
    for n in names:
        got = sorted(map(tuple, registry.QUERIES[n](spark, sf).collect()))
        assert len(got) == len(want[n]) and all(a == pytest.approx(b, abs=1.5e-4) for a, b in zip(got, want[n], strict=True)), n


def test_gram_of_times_adds_slices(spark, monkeypatch):
    from groupshift.operators import direction, relax

    x = np.random.default_rng(5).normal(size=(40, 7))
    rows = [(i, t, float(x[i, t])) for i in range(40) for t in range(7)]
    columns = relax.columns_of(spark.createDataFrame(rows, "series_id long, t long, cusum double"))
    monkeypatch.setattr(direction, "GRAM_SERIES", 3)
    monkeypatch.setattr(direction, "SLICE_CELLS", 1)
    times, gram = direction.gram_of_times(columns)
    assert times == list(range(7)) and gram == pytest.approx(x.T @ x)
    got = {r.series_id: r.v for r in direction.leading_left(columns, "gram").collect()}
    assert [got[i] for i in range(40)] == pytest.approx(list(kernels.leading_left(x)))


def test_direction_of_cells_makes_no_column_of_all_series(spark, sf, monkeypatch):
    """direction_lam0: the rows of the series give the Gram matrix of the times, whole columns are gathered beyond the bound on times only."""
    from groupshift.plans import registry

    x = np.random.default_rng(6).normal(size=(40, 7))
    cells = spark.createDataFrame([(i, t, float(x[i, t])) for i in range(40) for t in range(7)], "series_id long, t long, m double").repartition(3)
    want = list(kernels.leading_left(x))
    with monkeypatch.context() as few:
        few.setattr(direction, "GRAM_TIMES", 6)
        assert [r.v for r in direction.leading_of_cells(cells, 7).orderBy("series_id").collect()] == pytest.approx(want)

    def never(*_):
        raise MemoryError

    monkeypatch.setattr(direction, "columns_of", never)
    monkeypatch.setattr(relax, "columns_of", never)
    monkeypatch.setattr(direction, "SLICE_CELLS", 1)
    assert [r.v for r in direction.leading_of_cells(cells, 7).orderBy("series_id").collect()] == pytest.approx(want)
    assert direction.leading_of_cells(cells.where("t < 0"), 7).count() == 0
    zero = direction.leading_of_cells(cells.withColumn("m", F.lit(0.0)), 7).collect()
    assert len(zero) == 40 and not any(r.v for r in zero)
    assert registry.QUERIES["direction_lam0"](spark, sf).count() == 100


def test_sin_theta_brings_no_side_of_the_series_to_the_driver(spark, sf, monkeypatch):
    """With many series neither their Gram matrix nor the direction is on the driver; the loss stays."""
    from groupshift.plans import registry

    want = registry.QUERIES["sin_theta"](spark, sf).first().loss

    def never(*_):
        raise MemoryError

    monkeypatch.setattr(direction, "GRAM_SERIES", 3)
    for name in ("_gram", "_oriented"):
        monkeypatch.setattr(direction, name, never)
    assert registry.QUERIES["sin_theta"](spark, sf).first().loss == pytest.approx(want, abs=1e-3)


def test_few_times_spare_the_driver_a_matrix_of_more_series(spark, monkeypatch):
    """sin_theta: series between the two bounds go by the times, if these are few; the loss is that of the SQL."""
    import duckdb

    from groupshift.operators import direction, relax
    from groupshift.plans import registry

    x = np.random.default_rng(7).normal(size=(40, 9))
    cells = spark.createDataFrame([(i, t, float(x[i, t])) for i in range(40) for t in range(9)], "series_id long, t long, cusum double")
    sides = [direction.side(relax.columns_of(cells)) for times in (40, 39, 9, 8) if not monkeypatch.setattr(direction, "GRAM_TIMES", times)]
    assert sides == ["series", "times", "times", "series"]

    def never(*_):
        raise MemoryError

    for name in ("_gram", "_oriented"):
        monkeypatch.setattr(direction, name, never)
    monkeypatch.setattr(direction, "GRAM_TIMES", 400)
    sf = "/root/testdata/sf0.1"  # 480 active series, 355 times
    with duckdb.connect() as c:
        for name in ("lineitem", "supplier"):
            c.sql(f"CREATE VIEW {name} AS FROM '{sf}/{name}.parquet'")
        want = c.sql(registry.ORACLES["sin_theta"]).fetchall()
    assert list(map(tuple, registry.QUERIES["sin_theta"](spark, sf).collect())) == want


def test_componentwise_of_series_that_never_vary(spark, sf, tmp_path):
    """Where all times tie b_componentwise has the earliest, as its SQL has on one thread; on several threads the SQL does not repeat its choice."""
    import duckdb

    from groupshift.plans import registry

    with duckdb.connect() as c:
        c.sql("SET threads = 1")
        c.sql(f"COPY (FROM '{sf}/lineitem.parquet' WHERE l_suppkey BETWEEN 10 AND 49) TO '{tmp_path}/lineitem.parquet'")
        c.sql(f"COPY (FROM '{sf}/supplier.parquet') TO '{tmp_path}/supplier.parquet'")
        for name in ("lineitem", "supplier"):
            c.sql(f"CREATE VIEW {name} AS FROM '{tmp_path}/{name}.parquet'")
        want = sorted(c.sql(registry.ORACLES["b_componentwise"]).fetchall())
    got = sorted(map(tuple, registry.QUERIES["b_componentwise"](spark, str(tmp_path)).collect()))
    assert got == want and sum(r[1:] == (1, 0.0) for r in got) == 50


def test_cusum_of_repeated_keys(spark, sf, tmp_path):
    """b_componentwise, cusum_blocked: a supplier that is given twice has each time twice, and sums take both rows of a time, as in SQL."""
    import duckdb

    from groupshift.plans import registry

    with duckdb.connect() as c:
        c.sql(f"COPY (FROM '{sf}/lineitem.parquet' WHERE l_suppkey < 30) TO '{tmp_path}/lineitem.parquet'")
        c.sql(f"COPY (FROM '{sf}/supplier.parquet' WHERE s_suppkey < 30 UNION ALL FROM '{sf}/supplier.parquet' WHERE s_suppkey IN (3, 25)) TO '{tmp_path}/supplier.parquet'")
        for name in ("lineitem", "supplier"):
            c.sql(f"CREATE VIEW {name} AS FROM '{tmp_path}/{name}.parquet'")
        for name in ("b_componentwise", "cusum_blocked"):
            want = sorted(c.sql(registry.ORACLES[name]).fetchall())
            got = sorted(map(tuple, registry.QUERIES[name](spark, str(tmp_path)).collect()))
            assert len(got) == len(want) == (30 if name == "b_componentwise" else 32 * 355)
            assert all(a[:2] == b[:2] and a[2] == pytest.approx(b[2], abs=2e-6) for a, b in zip(got, want, strict=True)), name


def test_panels_dealt_to_slices_give_the_same(spark, monkeypatch):
    """e3_planted_suppliers and e6_null_panels beyond the bound on cells: no matrix of the panel, the same points and threshold."""
    from groupshift.operators import wide
    from groupshift.plans import experiments

    p, n = 37, 24
    panel = panel_of(spark, np.random.default_rng(8).normal(size=(p, n)))
    small, long = gr.blocks(spark, p, 5, first=1), gr.single(panel)
    key = lambda r: (r.config_id, r.rep, r.method)

    def run():
        found = experiments.planted_compare(panel, small, sizes=(2.0, 6.0), reps=2).collect()
        xi = [multi.xi_permuted(panel, g, reps=6, stat=s) for g, s in ((small, "gsp"), (long, "gsp"), (small, "sparse_projection"))]
        return sorted(found, key=key), xi

    want, xi = run()
    monkeypatch.setattr(multi, "REPLICATED_CELLS", 10)
    monkeypatch.setattr(wide, "SLICE_CELLS", 200)
    got, other = run()
    assert other == pytest.approx(xi) and len(got) == len(want) == 20
    for a, b in zip(got, want, strict=True):
        assert (key(a), a.z_true, a.z_hat) == (key(b), b.z_true, b.z_hat) and a.stat == pytest.approx(b.stat)


def test_norm_of_a_long_group_is_taken_once(spark):
    """e6_null_panels: no lambda over a block's entries holds a fold of the whole block, whose cost is the square of the group's size; values as by the kernels."""
    p, n, lam = 1500, 6, 1.2
    x = np.random.default_rng(3).normal(size=(p, n)) * np.linspace(0.5, 2.5, n)
    groups = spark.createDataFrame([(int(i >= 1200), i + 1) for i in range(p)], "group_id long, series_id long")
    c = panel_of(spark, x).withColumnRenamed("x", "cusum")
    want = kernels.block_shrink(x, [np.arange(1200), np.arange(1200, p)], lam)
    columns = single.solved(c, groups, lam, "closed", True)
    long = relax.block_shrink(c, groups, lam)
    assert (want == 0).any() and want.any()
    for df, cells in ((columns, relax.to_long(columns)), (long, long)):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        bodies = [plan[m.end() :] for m in re.finditer(r"lambdafunction\(", plan)]
        assert bodies
        for body in bodies:
            depth, end = 1, 0
            while depth:
                depth += {"(": 1, ")": -1}.get(body[end], 0)
                end += 1
            assert "aggregate(" not in body[:end]
        assert matrix_of(cells, p, n) == pytest.approx(want, abs=1e-12)


def test_permuted_panels_below_the_bound_stay_off_the_driver(spark, monkeypatch):
    """e6_null_panels: from PERMUTED_CELLS on no matrix of the panel is made, and the threshold is the same; overlapping groups still go whole."""
    panel = panel_of(spark, np.random.default_rng(9).normal(size=(12, 10)))
    apart, over = gr.blocks(spark, 12, 4, first=1), gr.windows(spark, 12, 6, 3, first=1)
    want = [multi.xi_permuted(panel, g, reps=4) for g in (apart, over)]
    monkeypatch.setattr(multi, "PERMUTED_CELLS", 20)
    assert multi.xi_permuted(panel, over, reps=4) == pytest.approx(want[1])
    monkeypatch.setattr(multi, "as_matrix", None)
    assert multi.xi_permuted(panel, apart, reps=4) == pytest.approx(want[0])
