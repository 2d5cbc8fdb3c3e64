"""One query for each method, variant, baseline, measure, workload and operator, with DuckDB text where SQL can say it.

Location queries run on weekly supplier totals with one change planted in the first two blocks of ten suppliers.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.functions import metrics, sqlfuncs, theory, tuning
from groupshift.operators import baselines, intervals, locate, multi, norms, relax, relops, scale, single
from groupshift.operators import cusum as cu
from groupshift.operators import direction as di
from groupshift.operators import groups as gr
from groupshift.sources import panels, simulate
from groupshift.sources.tables import TABLES, table

from . import cost, experiments
from . import oracles as o

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

Z, SIZE, CHOSEN = 142, 3.0, (0, 1)
#: The published number of change-free panels behind a threshold, and as many random intervals.
NULLS, INTERVALS = 1000, 1000


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def rounded(df: DataFrame, places: int, *columns: str) -> DataFrame:
    """Doubles to so many places, without negative zeros."""
    return df.withColumns({c: F.round(F.col(c), places) + F.lit(0.0) for c in columns})


def r(expression: str, places: int = 6) -> str:
    return f"round({expression}, {places}) + 0.0"


# Panels that the queries share


def supplier_blocks(spark, sf) -> DataFrame:
    return gr.from_table(table(spark, sf, "supplier").select("s_suppkey", F.expr("s_suppkey div 10").alias("g")), "s_suppkey", "g")


def supplier_planted(spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(panel, groups, truth), the panel written once."""
    groups = supplier_blocks(spark, sf)
    panel, truth = panels.plant(scale.standardised(panels.supplier_week(spark, sf)), groups, [panels.Step(Z, CHOSEN, SIZE)])
    return relax.work_table(panel, "panel"), groups, truth


def window_planted(spark, sf):
    """(panel, groups, truth) over all vectors, a change planted in one of seven windows."""
    panel = panels.embedding_stream(spark, sf)
    n = panel.agg(F.max("t")).first()[0] or 0
    groups = gr.windows(spark, 64, 16, 8, first=1)
    panel, truth = panels.plant(scale.standardised(panel), groups, [panels.Step(2 * n // 5, (2,), 4.0)])
    return relax.work_table(panel, "panel"), groups, truth


PB = f"WITH RECURSIVE {o.supplier_week()},\n{o.SCALE},\n{o.planted((Z,), SIZE, (1,), 'series_id < 20')},\n{o.cusum()}"
PB_LEVEL = f"{PB},\n{o.BLOCKS},\n{o.LEVEL}"
PB_SHRUNK = f"{PB_LEVEL},\n{o.shrunk()}"
PA = f"WITH {o.NATION_WEEK},\n{o.SCALE},\n{o.cusum('std')}"
PE = f"WITH {o.EMBEDDING_STREAM},\n{o.SCALE},\n{o.planted(('(SELECT 2 * max(t) // 5 FROM raw)',), 4.0, (1,), 'series_id BETWEEN 17 AND 32')},\n{o.cusum()}"
WINDOWS = "grp AS (SELECT w::BIGINT AS group_id, (8 * w + i)::BIGINT AS series_id FROM range(7) AS a(w), range(1, 17) AS b(i))"


# CUSUM transforms


@query("cusum_supplier_week", f"{PB} SELECT series_id, t, {r('cusum')} AS cusum FROM cus")
def _(spark, sf):
    return rounded(cu.cusum(supplier_planted(spark, sf)[0]), 6, "cusum")


@query("cusum_blocked", ORACLES["cusum_supplier_week"])
def _(spark, sf):
    return rounded(cu.cusum_blocked(supplier_planted(spark, sf)[0], bucket=32), 6, "cusum")


HASH = "('0x' || substr(md5('{}:' || {}), 1, 12))::BIGINT"


def drawn_sql(n: int, count: int, seed: str) -> str:
    return f"""draws AS (SELECT q::INT AS q, {HASH.format(seed, 'q')} % {n * (n - 1) // 2} AS k FROM range({count}) AS a(q)),
        roots AS (SELECT q, k, (SELECT max(x) FROM range(1, {n}) AS b(x) WHERE x * (x - 1) // 2 <= k)::BIGINT AS r FROM draws),
        itv AS (SELECT q, (k - r * (r - 1) // 2)::BIGINT AS s, (r + 1)::BIGINT AS e FROM roots)"""


@query("intervals", f"""WITH draws AS (SELECT c_custkey AS q, {HASH.format('intervals', 'c_custkey')} % {720 * 719 // 2} AS k FROM customer),
    roots AS (SELECT q, k, floor((1 + sqrt(1 + 8 * k)) / 2)::BIGINT AS r FROM draws) SELECT q, (k - r * (r - 1) // 2)::BIGINT AS s, (r + 1)::BIGINT AS e FROM roots""")  # fmt: skip
def _(spark, sf):
    """An interval for each customer."""
    return intervals.draw_for(table(spark, sf, "customer").select(F.col("c_custkey").alias("q")), 720)


INTERVAL_CUSUM = """itc AS (
            SELECT q, s, e, p.series_id, p.t, ((p.t - s) * (h.pref - coalesce(l.pref, 0)) - (e - s) * (p.pref - coalesce(l.pref, 0)))
                   / sqrt((e - s)::DOUBLE * (p.t - s) * (e - p.t)) AS cusum
            FROM itv JOIN cus_p p ON p.t > s AND p.t < e JOIN cus_p h ON h.t = e AND h.series_id = p.series_id
                 LEFT JOIN cus_p l ON l.t = s AND l.series_id = p.series_id)"""
PA_INTERVALS = f"{PA},\n{drawn_sql(343, 20, 'pa')},\n{INTERVAL_CUSUM}"


def nation_std(spark, sf):
    return relax.work_table(scale.standardised(panels.nation_week(spark, sf)), "panel")


@query("cusum_intervals", f"{PA_INTERVALS} SELECT q, series_id, t, {r('cusum')} AS cusum FROM itc")
def _(spark, sf):
    return rounded(cu.cusum_intervals(nation_std(spark, sf), intervals.draw_intervals(spark, 343, 20, "pa")), 6, "cusum")


# Scales


@query("row_scale_mean", f"WITH {o.supplier_week()},\n{o.SCALE} SELECT series_id, {r('sigma')} AS sigma FROM scales")
def _(spark, sf):
    return rounded(scale.row_scale(panels.supplier_week(spark, sf)), 6, "sigma")


@query("row_scale_median", f"""WITH {o.supplier_week()},
    d AS (SELECT series_id, x - lag(x) OVER (PARTITION BY series_id ORDER BY t) AS d FROM raw),
    m AS (SELECT series_id, median(d) AS m FROM d WHERE d IS NOT NULL GROUP BY series_id)
    SELECT series_id, {r('median(abs(d - m)) * (1.4826 / sqrt(2))')} AS sigma FROM d JOIN m USING (series_id) WHERE d IS NOT NULL GROUP BY series_id""")  # fmt: skip
def _(spark, sf):
    return rounded(scale.row_scale(panels.supplier_week(spark, sf), "median_ad"), 6, "sigma")


@query("standardised", f"WITH {o.NATION_WEEK},\n{o.SCALE} SELECT series_id, t, {r('x')} AS x FROM std")
def _(spark, sf):
    return rounded(scale.standardised(panels.nation_week(spark, sf)), 6, "x")


# Relaxation


@query("block_shrink", f"{PB_SHRUNK} SELECT series_id, t, {r('m')} AS m FROM shr")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    lam, _, _ = single.level(panel, groups, None)
    return rounded(relax.block_shrink(cu.cusum(panel), groups, lam), 6, "m")


@query("block_survivors", f"""{PB_SHRUNK} SELECT group_id, count(*) AS blocks, {r('max(norm)')} AS longest
    FROM norms, lev WHERE norm > lam * sqrt(p_g) GROUP BY group_id""")  # fmt: skip
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    lam, _, _ = single.level(panel, groups, None)
    return rounded(relax.active_groups(cu.cusum(panel), groups, lam), 6, "longest")


@query("soft_threshold", f"{PB} SELECT series_id, t, {r('sign(cusum) * (abs(cusum) - 2)')} AS m FROM cus WHERE abs(cusum) > 2")
def _(spark, sf):
    return rounded(baselines.soft_threshold(cu.cusum(supplier_planted(spark, sf)[0]), 2.0), 6, "m")


@query("one_group", f"{PB}, grp AS (SELECT DISTINCT 0 AS group_id, series_id FROM panel), lev AS (SELECT 1.05 AS lam),\n{o.shrunk()} SELECT series_id, t, {r('m')} AS m FROM shr")
def _(spark, sf):
    panel, _, _ = supplier_planted(spark, sf)
    return rounded(relax.block_shrink(cu.cusum(panel), gr.single(panel), 1.05), 6, "m")


def _cg_sql(steps: int) -> str:
    out = f"""{PE},\n{WINDOWS},\nlev AS (SELECT (1 + sqrt(4 * ln(7 * max(t)) / 16)) / 2 AS lam FROM panel),
        s0 AS MATERIALIZED (SELECT series_id, t, cusum AS c, cusum / sqrt((SELECT sum(cusum * cusum) FROM cus)) AS m FROM cus)"""
    for k in range(1, steps + 1):
        p = f"s{k - 1}"
        out += f""",
        n{k} AS (SELECT group_id, t, sqrt(sum(m * m)) AS norm FROM {p} JOIN grp USING (series_id) GROUP BY ALL),
        g{k} AS MATERIALIZED (SELECT series_id, t, any_value(c) AS c, any_value(m) AS m, any_value(c) - sum(lam * 4 * m / norm) AS g
               FROM {p} JOIN grp USING (series_id) JOIN n{k} USING (group_id, t), lev GROUP BY series_id, t),
        w{k} AS (SELECT sqrt(sum(g * g)) AS len, sum(m * g) / sqrt(sum(g * g)) AS cosine FROM g{k}),
        s{k} AS MATERIALIZED (SELECT series_id, t, c, ({k} * m + 2 * g / len) / sqrt({k * k} + {4 * k} * cosine + 4) AS m FROM g{k}, w{k})"""
    return out + f" SELECT series_id, t, {r('m')} AS m FROM s{steps}"


@query("cg_overlap_5", _cg_sql(5))
def _(spark, sf):
    panel, groups, _ = window_planted(spark, sf)
    lam, _, _ = single.level(panel, groups, None)
    columns = relax.work_table(relax.columns_of(cu.cusum(panel)), "columns")
    return rounded(relax.to_long(relax.conditional_gradient(columns, groups, lam, eps=0.0, max_iter=5, save_every=3)), 6, "m")


@query("columnwise_overlap")
def _(spark, sf):
    panel, groups, _ = window_planted(spark, sf)
    lam, _, _ = single.level(panel, groups, None)
    return rounded(relax.to_long(relax.columnwise_dual(relax.columns_of(cu.cusum(panel)), groups, lam)), 4, "m")


# Directions


DIRECTION = f"{PB_SHRUNK},\n{o.direction()}"


def supplier_solved(spark, sf):
    panel, groups, truth = supplier_planted(spark, sf)
    lam, disjoint, _ = single.level(panel, groups, None)
    c = relax.work_table(cu.cusum(panel), "cusum")
    return panel, c, relax.work_table(single.solved(c, groups, lam, "auto", disjoint), "relaxed"), truth


@query("direction_gram", f"{DIRECTION} SELECT series_id, {r('v', 4)} AS v FROM dir")
def _(spark, sf):
    return rounded(di.leading_left(supplier_solved(spark, sf)[2], "gram"), 4, "v")


@query("direction_power", ORACLES["direction_gram"])
def _(spark, sf):
    return rounded(di.leading_left(supplier_solved(spark, sf)[2], "power", steps=40, tol=1e-9), 4, "v")


@query("direction_sketch", ORACLES["direction_gram"])
def _(spark, sf):
    return rounded(di.leading_left(supplier_solved(spark, sf)[2], "sketch"), 4, "v")


@query("direction_lam0", f"{PB}, shr AS (SELECT series_id, t, cusum AS m FROM cus),\n{o.direction()} SELECT series_id, {r('v', 4)} AS v FROM dir")
def _(spark, sf):
    panel = supplier_planted(spark, sf)[0]
    n = panel.agg(F.max("t")).first()[0] or 0
    return rounded(di.leading_of_cells(cu.cusum_of(panel, n).withColumnRenamed("cusum", "m"), n), 4, "v")


# Location


KNOWN = f"{PB}, dir AS (SELECT series_id, 1 / sqrt(count(*) OVER ()) AS v FROM hit),\n{o.located()} {o.PEAK}"


@query("locate_known_direction", KNOWN)
def _(spark, sf):
    panel, _, truth = supplier_planted(spark, sf)
    v = truth.select("series_id", (F.col("theta") / SIZE).alias("v"))
    return rounded(locate.locate(v, cu.cusum(panel)), 4, "stat")


@query("locate_project_first", KNOWN)
def _(spark, sf):
    panel, _, truth = supplier_planted(spark, sf)
    v = truth.select("series_id", (F.col("theta") / SIZE).alias("v"))
    return rounded(locate.locate(v, panel, on="data"), 4, "stat")


@query("b_oracle", KNOWN)
def _(spark, sf):
    panel, _, truth = supplier_planted(spark, sf)
    return rounded(baselines.oracle(cu.cusum(panel), truth), 4, "stat")


@query("single_supplier_week", f"{DIRECTION},\n{o.located()} {o.PEAK}")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return rounded(single.detect_single(panel, groups).point, 4, "stat")


@query("single_overlap")
def _(spark, sf):
    panel, groups, _ = window_planted(spark, sf)
    found = [("columnwise", single.detect_single(panel, groups)), ("iterative", single.detect_single(panel, groups, solver="iterative"))]
    parts = [f.point.select(F.lit(name).alias("solver"), "z", F.round("stat", 2).alias("stat")) for name, f in found]
    return parts[0].unionByName(parts[1])


HALVES = f"""{o.supplier_week()},\n{o.SCALE},\n{o.planted((Z,), SIZE, (1,), 'series_id < 20')},
    odd AS (SELECT series_id, (t + 1) // 2 AS t, x FROM panel WHERE t % 2 = 1), even AS (SELECT series_id, t // 2 AS t, x FROM panel WHERE t % 2 = 0),
    {o.cusum('odd', 'codd')},\n{o.cusum('even', 'ceven')},\n{o.BLOCKS},\n{o.LEVEL},\n{o.shrunk('codd')},\n{o.direction()},\n{o.located('dir', 'ceven')}"""


@query("split_supplier_week", f"WITH RECURSIVE {HALVES} SELECT (2 * arg_max(t, s))::BIGINT AS z, round(max(s), 4) AS stat FROM curve")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return rounded(single.detect_single_split(panel, groups).point, 4, "stat")


# Baselines


def baseline(name: str, curve: str, run):
    @query(name, f"{PB}, curve AS ({curve}) {o.PEAK}")
    def _(spark, sf):
        return rounded(run(cu.cusum(supplier_planted(spark, sf)[0])), 4, "stat")


RANKED = """(SELECT t, row_number() OVER w AS m, sum(a) OVER w AS top, sum(a * a) OVER w AS top2, sum(a) OVER (PARTITION BY t) AS whole, count(*) OVER (PARTITION BY t) AS p
    FROM (SELECT series_id, t, abs(cusum) AS a FROM cus) WINDOW w AS (PARTITION BY t ORDER BY a DESC, series_id ROWS UNBOUNDED PRECEDING))"""
baseline("b_l2", "SELECT t, sqrt(sum(cusum * cusum)) AS s FROM cus GROUP BY t", baselines.l2)
baseline("b_linf", "SELECT t, max(abs(cusum)) AS s FROM cus GROUP BY t", baselines.linf)
baseline("b_double_cusum", f"SELECT t, max(sqrt(m * (2 * p - m) / (2.0 * p)) * (top / m - (whole - top) / (2 * p - m))) AS s FROM {RANKED} GROUP BY t", baselines.double_cusum)
baseline("b_scan", f"SELECT t, max((top2 - m) / sqrt(2.0 * m)) AS s FROM {RANKED} GROUP BY t", baselines.scan)
baseline("b_sparsified", "SELECT t, sum(abs(cusum)) AS s FROM cus WHERE abs(cusum) > 3 GROUP BY t", lambda c: baselines.sparsified(c, 3.0))


@query("b_componentwise", f"{PB} SELECT series_id, arg_max(t, abs(cusum))::BIGINT AS z, {r('max(abs(cusum))', 4)} AS stat FROM cus GROUP BY series_id")
def _(spark, sf):
    return rounded(baselines.componentwise(cu.cusum(supplier_planted(spark, sf)[0])), 4, "stat")


@query("b_sparse_projection", f"""{PB}, lv AS (SELECT sqrt(ln(count(DISTINCT series_id) * ln(max(t) + 1)) / 2) AS lam FROM cus),
    shr AS (SELECT series_id, t, sign(cusum) * (abs(cusum) - lam) AS m FROM cus, lv WHERE abs(cusum) > lam),\n{o.direction()},\n{o.located()} {o.PEAK}""")  # fmt: skip
def _(spark, sf):
    return rounded(baselines.sparse_projection(relax.work_table(cu.cusum(supplier_planted(spark, sf)[0]), "cusum"))[0], 4, "stat")


# Several changes


TRIPLE = (180, 360, 540)


def events_planted(spark, sf):
    panel = scale.standardised(panels.event_hour(spark, sf))
    groups = gr.blocks(spark, 50, 10)
    panel, _ = panels.plant(panel, groups, [panels.Step(z, (0, 1), 2.0 * m) for z, m in zip(TRIPLE, (1.0, 1.5, 2.0), strict=True)])
    return relax.work_table(panel, "panel"), groups


PD = f"WITH {o.event_hour()},\n{o.SCALE},\n{o.planted(TRIPLE, 2.0, (1.0, 1.5, 2.0), 'series_id < 20')},\n{o.cusum()},\n{drawn_sql(720, 60, 'pd')},\n{INTERVAL_CUSUM}"


@query("wbs_candidates_l2", f"""{PD}, curve AS (SELECT q, s, e, t, sqrt(sum(cusum * cusum)) AS v FROM itc GROUP BY ALL)
    SELECT q, s, e, arg_max(t, v)::BIGINT AS b, {r('max(v)', 4)} AS stat FROM curve GROUP BY q, s, e""")  # fmt: skip
def _(spark, sf):
    panel, groups = events_planted(spark, sf)
    found = multi.interval_candidates(panel, groups, intervals.draw_intervals(spark, 720, 60, "pd"), 1.0, "l2", "distributed")
    return rounded(found, 4, "stat")


CANDIDATES = [(0, 10, 300, 180, 9.1), (1, 150, 420, 360, 12.5), (2, 330, 700, 540, 20.25), (3, 0, 720, 541, 19.5), (4, 200, 340, 250, 2.0), (5, 5, 190, 181, 4.0), (6, 380, 520, 400, 6.5), (7, 100, 170, None, 0.0)]
_VALUES = ", ".join(f"({q}, {s}, {e}, {'NULL' if b is None else b}, {stat})" for q, s, e, b, stat in CANDIDATES)


@query("wbs_recursion", f"""WITH RECURSIVE cand(q, s, e, b, stat) AS (VALUES {_VALUES}),
    seg(lo, hi, depth, z, stat, q) AS (
        SELECT 0, 720, 0, NULL::INT, NULL::DOUBLE, NULL::INT
        UNION ALL
        SELECT x.lo, x.hi, depth + 1, k.z, k.stat, k.q FROM (
            SELECT lo, hi, depth, arg_max(b, c.stat) AS z, max(c.stat)::DOUBLE AS stat, arg_max(c.q, c.stat) AS q
            FROM (SELECT DISTINCT lo, hi, depth FROM seg) g JOIN cand c ON g.lo <= c.s AND c.e <= g.hi AND c.b IS NOT NULL GROUP BY lo, hi, depth) k,
            LATERAL (SELECT k.lo AS lo, k.z AS hi UNION ALL SELECT k.z, k.hi) x WHERE k.stat >= 5)
    SELECT (row_number() OVER (ORDER BY z) - 1)::INT AS cp_id, z::BIGINT AS z, stat, depth::INT AS depth, q::INT AS q
    FROM (SELECT DISTINCT z, stat, depth - 1 AS depth, q FROM seg WHERE z IS NOT NULL)""")  # fmt: skip
def _(spark, sf):
    return multi.recurse(spark.createDataFrame(CANDIDATES, multi.CANDIDATE), 720, 5.0)


@query("multi_event_hour")
def _(spark, sf):
    panel, groups = events_planted(spark, sf)
    return rounded(multi.detect_multiple(panel, groups, multi.xi_permuted(panel, groups, reps=NULLS), intervals=INTERVALS), 4, "stat")


@query("multi_sparse_projection")
def _(spark, sf):
    panel, groups = events_planted(spark, sf)
    xi = multi.xi_permuted(panel, groups, reps=NULLS, stat="sparse_projection")
    return rounded(multi.detect_multiple(panel, groups, xi, intervals=INTERVALS, stat="sparse_projection"), 4, "stat")


@query("multi_distributed")
def _(spark, sf):
    panel, groups = events_planted(spark, sf)
    some = intervals.draw_intervals(spark, 720, 30, "pd")
    return rounded(multi.interval_candidates(panel, groups, some, mode="distributed", steps=12), 3, "stat")


@query("binseg_l2")
def _(spark, sf):
    panel, groups = events_planted(spark, sf)
    return rounded(multi.detect_multiple(panel, groups, 14.0, 1.0, intervals="segment", stat="l2"), 4, "stat")


@query("xi_null")
def _(spark, sf):
    lam = tuning.lambda_practical(200, 5, 10)
    rows = [(stat, multi.xi_monte_carlo(spark, 50, 200, kernels.blocks(50, 10), lam, 100, stat)) for stat in ("gsp", "sparse_projection")]
    return rounded(spark.createDataFrame(rows, "stat string, xi double"), 4, "xi")


# Tuning and theory


SETTINGS = [(1000, 10, 100), (1000, 10, 50), (1000, 10, 200), (1000, 19, 100), (1000, 25, 20), (1000, 25, 40), (1200, 50, 10), (1200, 100, 10)]


@query("tuning_values", f"""WITH s(n, g, q) AS (VALUES {', '.join(map(str, SETTINGS))})
    SELECT n::BIGINT AS n, g::BIGINT AS g, q::BIGINT AS least_size, round(1 + sqrt(4 * ln(g * n) / q), 6) AS theory, round((1 + sqrt(4 * ln(g * n) / q)) / 2, 6) AS practical,
           round(1 + sqrt(2 * ln(1 / power(n * g, -2.0)) / q), 6) AS tail, round(1 + sqrt(4 * ln(n)), 6) AS univariate, round(sqrt(ln(g * q * ln(n)) / 2), 6) AS sparse FROM s""")  # fmt: skip
def _(spark, sf):
    rows = [
        (n, g, q, tuning.lambda_theory(n, g, q), tuning.lambda_practical(n, g, q), tuning.lambda_tail((n * g) ** -2.0, q), tuning.lambda_univariate(n), tuning.lambda_sparse(g * q, n))
        for n, g, q in SETTINGS
    ]
    names = ("theory", "practical", "tail", "univariate", "sparse")
    return rounded(spark.createDataFrame(rows, "n long, g long, least_size long, " + ", ".join(f"{x} double" for x in names)), 6, *names)


@query("lambda_grid", f"""WITH n AS (SELECT max({o.days('o_orderdate', '1995-01-01', 7)}) AS n FROM orders),
    g AS (SELECT count(*) AS g, min(p_g) AS q FROM (SELECT c_nationkey, count(DISTINCT c_custkey) AS p_g FROM customer GROUP BY c_nationkey))
    SELECT i::INT AS i, round(0.1 * power(30, i / 6.0), 6) AS multiplier, round(0.1 * power(30, i / 6.0) * (1 + sqrt(4 * ln(g * n) / q)), 6) AS lam FROM range(7) AS a(i), n, g""")  # fmt: skip
def _(spark, sf):
    """Levels for the weeks of the orders and the customers in groups by nation."""
    profile = gr.profile(gr.from_table(table(spark, sf, "customer"), "c_custkey", "c_nationkey")).first()
    n = table(spark, sf, "orders").agg(F.max(panels.period(F.col("o_orderdate"), "1995-01-01", 7))).first()[0]
    levels = tuning.lambda_grid(n, profile["g"], profile["least_size"])
    rows = [(i, m, lam) for i, (m, lam) in enumerate(zip(tuning.GRID, levels, strict=True))]
    return rounded(spark.createDataFrame(rows, "i int, multiplier double, lam double"), 6, "multiplier", "lam")


@query("signal_cusum", f"""WITH panel AS (SELECT 1::BIGINT AS series_id, t::BIGINT AS t, (t > 400)::INT::DOUBLE AS x FROM range(1, 1001) AS a(t)),
    {o.cusum()} SELECT t, {r('cusum')} AS signal FROM cus""")  # fmt: skip
def _(spark, sf):
    rows = [(t + 1, x) for t, x in enumerate(theory.signal_profile(1000, 400))]
    return rounded(spark.createDataFrame(rows, "t long, signal double"), 6, "signal")


@query("theory_bounds", f"""WITH c AS (SELECT unnest([1.0, 2.0, 4.0, 8.0, 16.0])::DOUBLE AS size, 1000.0::DOUBLE AS n, 0.4::DOUBLE AS tau, 60.0::DOUBLE AS k, 12.0::DOUBLE AS s, 120.0::DOUBLE AS g),
    e AS (SELECT sum(power(CASE WHEN t <= 400 THEN sqrt(t / (1000.0 * (1000 - t))) * 600 ELSE sqrt((1000 - t) / (1000.0 * t)) * 400 END, 2)) AS e FROM range(1, 1000) AS a(t))
    SELECT size, {r('32 * (1 + sqrt(4 * ln(g * n) / 5)) * sqrt(k) / (sqrt(n) * tau * size)', 9)} AS upper,
           {r('sqrt((k + s * ln(g * n)) / (n * tau * tau * size * size))', 9)} AS simplified,
           {r('least(1 / 72.0, sqrt((k + s * ln(g / s)) / (n * tau * size * size)) / (72 * sqrt(3)))', 9)} AS lower,
           least(k, (s - 1) * ln(g / s)) >= 20 AS lower_holds, {r('(1 + sqrt(4 * ln(n))) / (n * size * size)', 9)} AS location, {r('size * sqrt(e)', 6)} AS operator_norm FROM c, e""")  # fmt: skip
def _(spark, sf):
    rows = []
    for size in experiments.DYADIC:
        lower, holds = theory.lower_bound(60, 12, 120, 1000, 0.4, size)
        rows.append((size, theory.direction_rate(tuning.lambda_theory(1000, 120, 5), 60, 1000, 0.4, size), theory.simplified_rate(60, 12, 120, 1000, 0.4, size), lower, holds, theory.location_rate(1000, size)[0], theory.operator_norm(1000, 400, size)))
    found = spark.createDataFrame(rows, "size double, upper double, simplified double, lower double, lower_holds boolean, location double, operator_norm double")
    return rounded(rounded(found, 9, "upper", "simplified", "lower", "location"), 6, "operator_norm")


@query("null_exceedance")
def _(spark, sf):
    delta = 1e-4
    stats = experiments.null_statistics(spark, 60, 100, 6, delta, 200)
    return metrics.null_exceedance(stats, tuning.lambda_tail(delta, 6), theory.null_tail(delta, 100, 10))


# Simulation


UNIFORM = "((('0x' || substr(md5('noise:{}:' || rep || ':' || series_id || ':' || t), 1, 12))::BIGINT + 0.5) / 281474976710656.0)"


@query("simulated_cells", f"""SELECT rep::INT AS rep, series_id::BIGINT AS series_id, t::BIGINT AS t,
    {r(f"sqrt(-2 * ln({UNIFORM.format('a')})) * cos(2 * pi() * {UNIFORM.format('b')})")} AS x
    FROM range(2) AS a(rep), range(1, 21) AS b(series_id), range(1, 101) AS c(t)""")  # fmt: skip
def _(spark, sf):
    return rounded(simulate.noise(spark, 20, 100, reps=2), 6, "x")


# Norms and groups


LAST = "vec AS (SELECT series_id, cusum AS v FROM cus WHERE t = 142)"


def supplier_column(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return cu.cusum(panel).where(F.col("t") == Z).select("series_id", F.col("cusum").alias("v")), groups


@query("vector_norms", f"{PB}, {LAST} SELECT count(*) FILTER (v <> 0) AS l0, {r('sum(abs(v))')} AS l1, {r('sqrt(sum(v * v))')} AS l2, {r('max(abs(v))')} AS linf FROM vec")
def _(spark, sf):
    return rounded(norms.vec_norms(supplier_column(spark, sf)[0]), 6, "l1", "l2", "linf")


@query("phi_map", f"{PB},\n{o.BLOCKS},\n{LAST} SELECT group_id, {r('sqrt(sum(v * v))')} AS norm FROM vec JOIN grp USING (series_id) GROUP BY group_id")
def _(spark, sf):
    return rounded(norms.phi(*supplier_column(spark, sf)), 6, "norm")


@query("group_norm", f"{PB_SHRUNK} SELECT {r('sum(sqrt(p_g) * norm)', 4)} AS group_norm FROM norms")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return rounded(norms.group_norm(cu.cusum(panel), groups), 4, "group_norm")


@query("group_dual_norm", f"{PB_SHRUNK} SELECT {r('max(norm / sqrt(p_g))')} AS dual_norm FROM norms")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return rounded(norms.dual_norm(cu.cusum(panel), groups), 6, "dual_norm")


@query("fro_inner", f"""{PB}, {o.cusum('std', 'c0')} SELECT {r('sqrt(sum(a.cusum * a.cusum))', 4)} AS frobenius, {r('sum(a.cusum * b.cusum)', 4)} AS "inner"
    FROM cus a JOIN c0 b USING (series_id, t)""")  # fmt: skip
def _(spark, sf):
    a = cu.cusum(supplier_planted(spark, sf)[0])
    b = cu.cusum(scale.standardised(panels.supplier_week(spark, sf)))
    return rounded(norms.frobenius(a).join(norms.inner(a, b)), 4, "frobenius", "inner")


@query("spectral_norms")
def _(spark, sf):
    return rounded(norms.spectral(relax.columns_of(cu.cusum(supplier_planted(spark, sf)[0]))), 4, "operator", "nuclear")


@query("restrict", f"WITH {o.NATION_WEEK} SELECT series_id, t, x FROM raw WHERE t BETWEEN 50 AND 60 AND series_id IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)")
def _(spark, sf):
    some = table(spark, sf, "nation").where("n_regionkey = 2").select(F.col("n_nationkey").cast("long").alias("series_id"))
    return norms.restrict(panels.nation_week(spark, sf), some, 50, 60)


@query("groups_profile", """WITH g(name, group_id, series_id) AS (
        SELECT 'blocks', i // 10, i FROM range(100) AS a(i) UNION ALL
        SELECT 'windows', w, 50 * w + i FROM range(19) AS a(w), range(100) AS b(i) UNION ALL
        SELECT 'hierarchy', n_regionkey, n_nationkey FROM nation UNION ALL SELECT 'hierarchy', 1000000 + n_nationkey, n_nationkey FROM nation),
    s AS (SELECT *, row_number() OVER (PARTITION BY name ORDER BY p_g DESC) AS k FROM (SELECT name, group_id, count(*) AS p_g FROM g GROUP BY ALL)),
    c AS (SELECT name, series_id, count(*) AS c FROM g GROUP BY ALL),
    x AS (SELECT name, count(*) AS g, min(p_g) AS least_size, sum(p_g)::BIGINT AS sum_sizes, sum(p_g) FILTER (k <= 3)::BIGINT AS top_s FROM s GROUP BY name),
    y AS (SELECT name, count(*) AS p, max(c) AS overlap FROM c GROUP BY name)
    SELECT name, p, g, least_size, overlap, sum_sizes, top_s, overlap = 1 AS disjoint FROM x JOIN y USING (name)""")  # fmt: skip
def _(spark, sf):
    nation = table(spark, sf, "nation")
    kinds = {
        "blocks": gr.blocks(spark, 100, 10), "windows": gr.windows(spark, 1000, 100, 50),
        "hierarchy": gr.union(gr.from_table(nation, "n_nationkey", "n_regionkey"), gr.from_table(nation, "n_nationkey", "n_nationkey")),
    }
    parts = [gr.profile(g).select(F.lit(name).alias("name"), "*") for name, g in kinds.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("cover_antijoin", "SELECT s_suppkey AS series_id FROM supplier WHERE s_nationkey NOT IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)")
def _(spark, sf):
    nation = table(spark, sf, "nation").where("n_regionkey < 3")
    supplier = table(spark, sf, "supplier")
    known = gr.from_table(supplier.join(nation, supplier["s_nationkey"] == nation["n_nationkey"]), "s_suppkey", "n_regionkey")
    return gr.uncovered(known, supplier.select(F.col("s_suppkey").alias("series_id")))


# Measures


RUNS = [("a", "gsp", i, 40, z) for i, z in enumerate((40, 41, 38, None, 45, 40))] + [("a", "l2", i, 40, z) for i, z in enumerate((44, 30, 60, 40, 12, 71))] + [("b", "gsp", 0, 40, 42), ("b", "l2", 0, 40, 42)]
_RUNS = "runs(config_id, method, rep, z_true, z_hat) AS (VALUES " + ", ".join(f"('{c}', '{m}', {i}, {z}, {'NULL' if h is None else h})" for c, m, i, z, h in RUNS) + ")"
_ERRORS = f"WITH {_RUNS}, err AS (SELECT config_id, method, avg(abs(coalesce(z_hat, 0) - z_true)) AS mean_abs, count(*) AS runs FROM runs GROUP BY ALL)"


def runs(spark):
    return spark.createDataFrame(RUNS, "config_id string, method string, rep int, z_true long, z_hat long")


_NATION_RUNS = f"""WITH {o.NATION_WEEK},\n{o.SCALE}, panel AS (SELECT series_id, t, x + (t > {Z})::INT AS x FROM std),\n{o.cusum()},
    sizes AS (SELECT 'cusum' AS method, series_id, t, round(abs(cusum), 6) AS a, sqrt(2 * ln(343)) AS least FROM cus UNION ALL
              SELECT 'difference', series_id, t - 1, round(abs(x - lag(x) OVER (PARTITION BY series_id ORDER BY t)), 6), 2 * sqrt(ln(343)) FROM panel),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY method, series_id ORDER BY a DESC, t) AS k FROM sizes WHERE a IS NOT NULL),
    runs AS (SELECT n_regionkey::VARCHAR AS config_id, method, n_nationkey::INT AS rep, {Z} AS z_true, CASE WHEN a >= least THEN t END AS z_hat
             FROM ranked JOIN nation ON n_nationkey = series_id WHERE k = 1)"""


def nation_runs(spark, sf):
    """A unit step planted in each nation's weeks, located by its CUSUM and by its largest difference; z_hat is null below the level of noise."""
    panel = nation_std(spark, sf).withColumn("x", F.col("x") + (F.col("t") > Z).cast("int"))
    level = math.sqrt(2 * math.log(343))
    jumps = scale.differences(panel).select(F.lit("difference").alias("method"), "series_id", (F.col("t") - 1).alias("t"), F.abs("d").alias("a"), F.lit(level * math.sqrt(2)).alias("least"))
    sizes = cu.cusum(panel).select(F.lit("cusum").alias("method"), "series_id", "t", F.abs("cusum").alias("a"), F.lit(level).alias("least")).unionByName(jumps)
    best = sizes.groupBy("method", "series_id", "least").agg(F.max(F.struct(F.round("a", 6).alias("a"), (-F.col("t")).alias("back"))).alias("b"))
    found = best.join(table(spark, sf, "nation"), F.col("n_nationkey") == F.col("series_id"))
    hat = F.when(F.col("b.a") >= F.col("least"), -F.col("b.back"))
    return found.select(F.col("n_regionkey").cast("string").alias("config_id"), "method", F.col("n_nationkey").cast("int").alias("rep"), F.lit(Z).cast("long").alias("z_true"), hat.alias("z_hat"))


@query("location_error", f"""{_NATION_RUNS}, err AS (SELECT config_id, method, avg(abs(coalesce(z_hat, 0) - z_true)) AS mean_abs, count(*) AS runs FROM runs GROUP BY ALL)
    SELECT config_id, method, round(mean_abs, 6) AS mean_abs, round(mean_abs / 343, 6) AS mean_share, runs FROM err""")  # fmt: skip
def _(spark, sf):
    return rounded(metrics.location_error(nation_runs(spark, sf), 343), 6, "mean_abs", "mean_share")


@query("winner_table", f"{_ERRORS} SELECT config_id, method, round(mean_abs, 6) AS mean_abs, (rank() OVER (PARTITION BY config_id ORDER BY mean_abs))::INT AS place FROM err")
def _(spark, sf):
    return rounded(metrics.winner_table(metrics.location_error(runs(spark), 100)), 6, "mean_abs")


@query("location_histogram", f"{_NATION_RUNS} SELECT method, ((z_hat - 1) // 10)::BIGINT AS bin, count(*) AS n FROM runs WHERE z_hat IS NOT NULL GROUP BY ALL")
def _(spark, sf):
    return metrics.location_histogram(nation_runs(spark, sf), 10)


@query("sin_theta", f"{DIRECTION}, tv AS (SELECT series_id, 1 / sqrt(count(*) OVER ()) AS w FROM hit) SELECT {r('sqrt(greatest(1 - power(sum(v * w), 2), 0))', 3)} AS loss FROM dir JOIN tv USING (series_id)")
def _(spark, sf):
    _, _, m, truth = supplier_solved(spark, sf)
    return rounded(metrics.sin_theta(di.leading_left(m, "gram"), truth.select("series_id", F.col("theta").alias("v"))), 3, "loss")


_POINTS = f"""weeks AS (SELECT c_nationkey::VARCHAR AS config_id, {o.days('o_orderdate', '1995-01-01', 7)} AS t, sum(o_totalprice::DECIMAL(18,4)) AS v, count(*) AS c
        FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY config_id ORDER BY v DESC, t) AS kv, row_number() OVER (PARTITION BY config_id ORDER BY c DESC, t) AS kc
        FROM weeks WHERE t BETWEEN 1 AND 343),
    pts AS (SELECT config_id, 't' AS side, t AS z FROM ranked WHERE kv <= 3 UNION ALL SELECT config_id, 'f', t FROM ranked WHERE kc <= 3)"""


def nation_points(spark, sf):
    """(config_id, side, z): each nation's three weeks of most money (t) and of most orders (f), earlier ones first."""
    orders = table(spark, sf, "orders").select("o_custkey", panels.period(F.col("o_orderdate"), "1995-01-01", 7).alias("z"), F.col("o_totalprice").cast(panels.MONEY).alias("price"))
    customers = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").cast("string").alias("config_id"))
    weeks = orders.where("z between 1 and 343").join(customers, F.col("o_custkey") == F.col("c_custkey")).groupBy("config_id", "z").agg(F.sum("price").alias("v"), F.count(F.lit(1)).alias("c"))
    weeks = relax.work_table(weeks, "weeks")
    top = lambda by: F.row_number().over(Window.partitionBy("config_id").orderBy(F.desc(by), "z"))
    sides = [weeks.withColumn("k", top(by)).where("k <= 3").select("config_id", F.lit(side).alias("side"), "z") for side, by in (("t", "v"), ("f", "c"))]
    return relax.work_table(sides[0].unionByName(sides[1]), "points")


@query("ari", f"""WITH {_POINTS}, lab AS (
        SELECT config_id, t, (SELECT count(*) FROM pts p WHERE p.config_id = c.config_id AND side = 't' AND p.z < t) AS a,
               (SELECT count(*) FROM pts p WHERE p.config_id = c.config_id AND side = 'f' AND p.z < t) AS b
        FROM (SELECT DISTINCT config_id FROM pts) c, range(1, 344) AS r(t)),
    ab AS (SELECT config_id, sum(n * (n - 1) / 2) AS c FROM (SELECT config_id, a, b, count(*) AS n FROM lab GROUP BY ALL) GROUP BY config_id),
    sa AS (SELECT config_id, sum(n * (n - 1) / 2) AS x FROM (SELECT config_id, a, count(*) AS n FROM lab GROUP BY ALL) GROUP BY config_id),
    sb AS (SELECT config_id, sum(n * (n - 1) / 2) AS y FROM (SELECT config_id, b, count(*) AS n FROM lab GROUP BY ALL) GROUP BY config_id)
    SELECT config_id, {r('(c - x * y / 58653) / ((x + y) / 2 - x * y / 58653)')} AS ari FROM ab JOIN sa USING (config_id) JOIN sb USING (config_id)""")  # fmt: skip
def _(spark, sf):
    pts = nation_points(spark, sf)
    return rounded(metrics.ari(pts.where("side = 't'"), pts.where("side = 'f'"), 343), 6, "ari")


@query("loglog_slope", "WITH c(g, x, y) AS (VALUES ('a', 1, 8.0), ('a', 2, 4.1), ('a', 4, 2.0), ('b', 1, 1.0), ('b', 3, 2.9)) SELECT g, round(regr_slope(ln(y), ln(x)), 6) AS slope FROM c GROUP BY g")
def _(spark, sf):
    curve = spark.createDataFrame([("a", 1, 8.0), ("a", 2, 4.1), ("a", 4, 2.0), ("b", 1, 1.0), ("b", 3, 2.9)], "g string, x int, y double")
    return rounded(metrics.loglog_slope(curve, "x", "y", ("g",)), 6, "slope")


SHIFT = 0.4


@query("best_lambda", f"""{PA}, at_z AS (SELECT series_id, n_regionkey AS g, cusum, count(*) OVER (PARTITION BY n_regionkey) AS p_g FROM cus JOIN nation ON n_nationkey = series_id WHERE t = {Z}),
    lev AS (SELECT i, 0.1 * power(30, i / 6.0) * (1 + sqrt(4 * ln(count(DISTINCT g) * 343) / min(p_g))) AS lam FROM range(7) AS a(i), at_z GROUP BY i),
    moved AS (SELECT i, lam, k.g AS changed, a.g, a.p_g, cusum + CASE WHEN a.g = k.g THEN {SHIFT} * sqrt({Z} * (343 - {Z}) / 343.0) ELSE 0 END AS c FROM at_z a, lev, (SELECT DISTINCT g FROM at_z) k),
    normed AS (SELECT *, sqrt(sum(c * c) OVER (PARTITION BY i, changed, g)) AS norm FROM moved),
    v AS (SELECT *, c * greatest(0, 1 - lam * sqrt(p_g) / norm) AS v FROM normed),
    losses AS (SELECT changed, i, round(sqrt(greatest(1 - coalesce(power(sum(v) FILTER (g = changed), 2) / nullif(sum(v * v) * count(*) FILTER (g = changed), 0), 0), 0)), 6) AS loss FROM v GROUP BY changed, i),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY changed ORDER BY loss, i) AS k FROM losses)
    SELECT changed::VARCHAR AS config_id, round(0.1 * power(30, i / 6.0), 6) AS multiplier, loss FROM ranked WHERE k = 1""")  # fmt: skip
def _(spark, sf):
    """A step planted in one region at a time; the multiplier whose shrunk CUSUM at that week comes nearest to its direction."""
    groups = gr.from_table(table(spark, sf, "nation"), "n_nationkey", "n_regionkey")
    profile = gr.profile(groups).first()
    lams = tuning.lambda_grid(343, profile["g"], profile["least_size"])
    levels = spark.createDataFrame([(round(m, 6), lam) for m, lam in zip(tuning.GRID, lams, strict=True)], "multiplier double, lam double")
    regions = groups.select(F.col("group_id").cast("string").alias("config_id")).distinct()
    tried = F.broadcast(regions.crossJoin(levels))
    at_z = cu.cusum(nation_std(spark, sf)).where(F.col("t") == Z).join(relax.sized_groups(groups), "series_id").crossJoin(tried)
    own = F.col("group_id").cast("string") == F.col("config_id")
    moved = at_z.withColumn("c", F.col("cusum") + F.when(own, SHIFT * math.sqrt(Z * (343 - Z) / 343)).otherwise(0.0))
    norm = F.sqrt(F.sum(F.col("c") * F.col("c")).over(Window.partitionBy("config_id", "multiplier", "group_id")))
    v = moved.withColumn("v", F.col("c") * F.greatest(F.lit(0.0), 1 - F.col("lam") * F.sqrt("p_g") / norm))
    loss = metrics.sin_theta(v, v.where(own).withColumn("v", F.lit(1.0)), ("config_id", "multiplier"))
    return metrics.best_lambda(rounded(loss, 6, "loss"))


@query("group_profile", f"WITH {o.NATION_WEEK},\n{o.SCALE} SELECT n_regionkey::BIGINT AS group_id, t, {r('sqrt(sum(x * x))')} AS norm FROM std JOIN nation ON n_nationkey = series_id GROUP BY ALL")
def _(spark, sf):
    groups = gr.from_table(table(spark, sf, "nation"), "n_nationkey", "n_regionkey")
    return rounded(metrics.group_profile(scale.standardised(panels.nation_week(spark, sf)), groups), 6, "norm")


# Relational operators


@query("scan_profile", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def _(spark, sf):
    out = None
    for t in TABLES:
        part = table(spark, sf, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n")).select("name", "n")
        out = part if out is None else out.unionByName(part)
    return out


CHANGES = [(50,), (120,), (300,)]


@query("segment_assign_asof", f"WITH {o.NATION_WEEK}, cp(z) AS (VALUES (50), (120), (300)) SELECT t, (SELECT count(*) FROM cp WHERE z < t)::INT AS segment FROM (SELECT DISTINCT t FROM raw)")
def _(spark, sf):
    times = panels.nation_week(spark, sf).select("t").distinct()
    return relops.asof_segment(times, spark.createDataFrame(CHANGES, "z long"))


_SEGMENTS = f"WITH {o.NATION_WEEK}, cp(z) AS (VALUES (50), (120), (300)), seg AS (SELECT series_id, (SELECT count(*) FROM cp WHERE z < t)::INT AS segment, x FROM raw), mean AS (SELECT series_id, segment, avg(x) AS mean, count(*) AS n FROM seg GROUP BY ALL)"


@query("segment_means", f"{_SEGMENTS} SELECT series_id, segment, round(mean, 4) AS mean, n FROM mean")
def _(spark, sf):
    return rounded(relops.segment_means(panels.nation_week(spark, sf), spark.createDataFrame(CHANGES, "z long")), 4, "mean")


@query("jump_vectors", f"{_SEGMENTS} SELECT (b.segment - 1)::INT AS cp_id, b.series_id, round(b.mean - a.mean, 4) AS v FROM mean a JOIN mean b ON a.series_id = b.series_id AND b.segment = a.segment + 1")
def _(spark, sf):
    return rounded(relops.jump_vectors(panels.nation_week(spark, sf), spark.createDataFrame(CHANGES, "z long")), 4, "v")


@query("range_join_intervals", f"WITH {drawn_sql(343, 40, 'rj')}, p AS (SELECT o_orderkey, {o.days('o_orderdate', '1995-01-01', 7)} AS t FROM orders) SELECT q, count(*) AS n, min(t) AS lo, max(t) AS hi FROM p JOIN itv ON t > s AND t <= e GROUP BY q")
def _(spark, sf):
    points = table(spark, sf, "orders").select(panels.period(F.col("o_orderdate"), "1995-01-01", 7).alias("t"))
    per_time = points.groupBy("t").agg(F.count(F.lit(1)).alias("c"))  # equal times are one point
    hit = relops.range_join(per_time, intervals.draw_intervals(spark, 343, 40, "rj"), 32)
    return hit.groupBy("q").agg(F.sum("c").alias("n"), F.min("t").alias("lo"), F.max("t").alias("hi"))


@query("densify_left", f"WITH {o.NATION_WEEK} SELECT series_id, count(*) AS n, count(*) FILTER (x = 0) AS empty FROM raw GROUP BY series_id")
def _(spark, sf):
    return panels.nation_week(spark, sf).groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("x") == 0, 1)).alias("empty"))


def nation_totals(spark, sf):
    nation = table(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    customer = table(spark, sf, "customer").select("c_custkey", "c_nationkey")
    orders = table(spark, sf, "orders").select("o_custkey", F.col("o_totalprice").cast(panels.MONEY).alias("price"), F.year("o_orderdate").alias("year"))
    joined = orders.join(customer, orders["o_custkey"] == customer["c_custkey"]).join(nation, customer["c_nationkey"] == nation["n_nationkey"])
    return joined.select("n_regionkey", "n_nationkey", "year", "price")


_TOTALS = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


def _subtotal_sql(how: str) -> str:
    return f"SELECT n_regionkey, n_nationkey, grouping_id(n_regionkey, n_nationkey)::INT AS level, sum(o_totalprice::DECIMAL(18,4))::DOUBLE AS total, count(*) AS n {_TOTALS} GROUP BY {how}"


@query("panel_rollup", _subtotal_sql("ROLLUP (n_regionkey, n_nationkey)"))
def _(spark, sf):
    return relops.subtotals(nation_totals(spark, sf), ["n_regionkey", "n_nationkey"], "price").withColumn("total", F.col("total").cast("double"))


@query("panel_cube", _subtotal_sql("CUBE (n_regionkey, n_nationkey)"))
def _(spark, sf):
    return relops.subtotals(nation_totals(spark, sf), ["n_regionkey", "n_nationkey"], "price", "cube").withColumn("total", F.col("total").cast("double"))


@query("grouping_sets", f"SELECT n_regionkey, year(o_orderdate)::INT AS year, sum(o_totalprice::DECIMAL(18,4))::DOUBLE AS total {_TOTALS} GROUP BY GROUPING SETS ((n_regionkey), (year(o_orderdate)::INT))")
def _(spark, sf):
    return relops.grouping_sets(nation_totals(spark, sf), [["n_regionkey"], ["year"]], "price").withColumn("total", F.col("total").cast("double"))


@query("pivot_regions", f"WITH t AS (SELECT year(o_orderdate)::INT AS year, n_regionkey, o_totalprice::DECIMAL(18,4) AS p {_TOTALS}) SELECT year, " + ", ".join(f"sum(p) FILTER (n_regionkey = {k})::DOUBLE AS region_{k}" for k in range(5)) + " FROM t GROUP BY year")
def _(spark, sf):
    wide = nation_totals(spark, sf).groupBy("year").pivot("n_regionkey", list(range(5))).agg(F.sum("price").cast("double"))
    return wide.select("year", *[F.col(str(k)).alias(f"region_{k}") for k in range(5)])


@query("diff_lag", f"WITH {o.NATION_WEEK}, d AS (SELECT series_id, t, x - lag(x) OVER (PARTITION BY series_id ORDER BY t) AS d FROM raw) SELECT series_id, t, round(d, 4) + 0.0 AS d FROM d WHERE d IS NOT NULL")
def _(spark, sf):
    return rounded(scale.differences(panels.nation_week(spark, sf)), 4, "d")


@query("rank_blocks", f"""{PB_SHRUNK}, k AS (SELECT group_id, t, round(norm, 6) AS norm FROM norms)
    SELECT group_id, t, norm, (row_number() OVER w)::INT AS rn, (rank() OVER v)::INT AS rk, (dense_rank() OVER v)::INT AS dr, (ntile(4) OVER w)::INT AS quarter
    FROM k WINDOW w AS (PARTITION BY t ORDER BY norm DESC, group_id), v AS (PARTITION BY t ORDER BY norm DESC)""")  # fmt: skip
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return relops.rank_blocks(rounded(norms.block_norms(cu.cusum(panel), groups), 6, "norm"))


@query("topk_peaks", f"{PB} SELECT series_id, t, a, rank::INT AS rank FROM (SELECT series_id, t, a, row_number() OVER (PARTITION BY series_id ORDER BY a DESC, t) AS rank FROM (SELECT series_id, t, round(abs(cusum), 6) AS a FROM cus)) WHERE rank <= 3")
def _(spark, sf):
    c = cu.cusum(supplier_planted(spark, sf)[0]).select("series_id", "t", F.round(F.abs("cusum"), 6).alias("a"))
    return relops.topk(c, ["series_id"], 3, "a")


_SETS = f"{PB}, a AS (SELECT DISTINCT arg_max(t, abs(cusum)) AS z FROM cus WHERE series_id < 50 GROUP BY series_id), b AS (SELECT DISTINCT arg_max(t, abs(cusum)) AS z FROM cus WHERE series_id >= 50 GROUP BY series_id)"


@query("setops_detections", f"{_SETS} SELECT 'common' AS op, z FROM (SELECT z FROM a INTERSECT SELECT z FROM b) UNION ALL SELECT 'only', z FROM (SELECT z FROM a EXCEPT SELECT z FROM b) UNION ALL SELECT 'either', z FROM (SELECT z FROM a UNION SELECT z FROM b)")
def _(spark, sf):
    found = baselines.componentwise(cu.cusum(supplier_planted(spark, sf)[0]))
    a, b = found.where("series_id < 50").select("z").distinct(), found.where("series_id >= 50").select("z").distinct()
    ops = {"common": relops.common(a, b), "only": relops.only_in(a, b), "either": relops.either(a, b)}
    parts = [df.select(F.lit(k).alias("op"), "z") for k, df in ops.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("calendar_buckets", f"""SELECT {o.days('o_orderdate', '1995-01-01', 7)} AS week, year(o_orderdate)::INT AS year, month(o_orderdate)::INT AS month, count(*) AS n,
    max(date_diff('day', DATE '1995-01-01', o_orderdate::DATE))::INT AS last_day FROM orders GROUP BY ALL""")  # fmt: skip
def _(spark, sf):
    rows = relops.bucket_time(table(spark, sf, "orders").select("o_orderdate"), "o_orderdate", "1995-01-01", 7)
    day = F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))
    return rows.groupBy(F.col("t").alias("week"), F.year("o_orderdate").alias("year"), F.month("o_orderdate").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(day).alias("last_day"))


_SHARE = "len(regexp_extract_all(text, '{}')) / greatest(length(text), 1)"


@query("text_features", f"""SELECT doc_id, round(ln(1.0 + length(text)), 6) AS log_chars, round(ln(1.0 + len(regexp_extract_all(text, '[^ \\t\\n\\r\\f\\x0B]+'))), 6) AS log_words,
    round(ln(1.0 + length(text) - length(replace(text, chr(10), ''))), 6) AS log_lines, round({_SHARE.format('[0-9]')}, 6) AS digit_share, round({_SHARE.format('[A-Z]')}, 6) AS upper_share,
    round({_SHARE.format('[.,;:!?]')}, 6) AS punct_share, round({_SHARE.format('[ \\n\\t]')}, 6) AS space_share,
    round(len(list_distinct(regexp_extract_all(text, '[^ \\t\\n\\r\\f\\x0B]+'))) / greatest(len(regexp_extract_all(text, '[^ \\t\\n\\r\\f\\x0B]+')), 1), 6) AS distinct_ratio FROM documents""")  # fmt: skip
def _(spark, sf):
    features = panels.text_features()
    return table(spark, sf, "documents").select("doc_id", *[F.round(c, 6).alias(k) for k, c in features.items()])


@query("embedding_panel", f"WITH {o.EMBEDDING_STREAM} SELECT series_id, t, x FROM raw")
def _(spark, sf):
    return panels.embedding_stream(spark, sf)


@query("event_props", "SELECT event_type, (props->>'$.k')::INT AS k, count(*) AS n, sum(value::DECIMAL(18,4))::DOUBLE AS total FROM events GROUP BY ALL")
def _(spark, sf):
    k = F.get_json_object("props", "$.k").try_cast("int")
    total = F.sum(F.col("value").cast(panels.MONEY)).cast("double")
    return table(spark, sf, "events").groupBy("event_type", k.alias("k")).agg(F.count(F.lit(1)).alias("n"), total.alias("total"))


@query("brand_return", f"""WITH c AS (SELECT regexp_extract(p_brand, '(\\d+)', 1)::BIGINT AS series_id, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate))::BIGINT AS t,
        sum((l_extendedprice / l_quantity)::DECIMAL(18,4))::DOUBLE / count(*) AS x FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL),
    k AS (SELECT * FROM c WHERE t BETWEEN 1 AND 82 QUALIFY count(*) OVER (PARTITION BY series_id) = 82),
    b AS (SELECT series_id, t, x / lag(x) OVER (PARTITION BY series_id ORDER BY t) AS q FROM k)
    SELECT series_id, t - 1 AS t, {r('ln(q)', 5)} AS x FROM b WHERE q IS NOT NULL""")  # fmt: skip
def _(spark, sf):
    return rounded(panels.brand_return(spark, sf), 5, "x")


@query("event_panel", f"WITH {o.event_hour()} SELECT series_id, t, x FROM raw")
def _(spark, sf):
    return panels.event_hour(spark, sf)


@query("chat_panel", """WITH p AS (SELECT conv_id, role, count(*)::DOUBLE AS n, avg(length(text)) AS mean, max(length(text))::DOUBLE AS most FROM conversations GROUP BY ALL),
    c AS (SELECT conv_id, row_number() OVER (ORDER BY conv_id) AS t FROM (SELECT DISTINCT conv_id FROM conversations WHERE role IN ('user', 'assistant'))),
    k AS (SELECT * FROM (VALUES ('user', 0), ('assistant', 3)) AS a(role, base), (VALUES ('n', 0), ('mean', 1), ('most', 2)) AS b(what, i))
    SELECT (base + i)::BIGINT AS series_id, t, round(coalesce(CASE what WHEN 'n' THEN n WHEN 'mean' THEN mean ELSE most END, 0), 6) AS x
    FROM c CROSS JOIN k LEFT JOIN p ON p.conv_id = c.conv_id AND p.role = k.role""")  # fmt: skip
def _(spark, sf):
    return rounded(panels.chat_stats(spark, sf), 6, "x")


@query("sql_functions", f"""WITH {o.NATION_WEEK}, p AS (SELECT series_id, t, sum(x) OVER (PARTITION BY series_id ORDER BY t) AS pref, sum(x) OVER (PARTITION BY series_id) AS tot FROM raw)
    SELECT series_id, round((100 * tot - 343 * pref) / sqrt(343.0 * 100 * 243), 4) AS c, round(1 + sqrt(4 * ln(5 * 343) / 5), 6) AS lam, 0.6::DOUBLE AS loss FROM p WHERE t = 100""")  # fmt: skip
def _(spark, sf):
    sqlfuncs.register(spark)
    cu.prefix(panels.nation_week(spark, sf)).createOrReplaceTempView("gs_prefix")
    return spark.sql(
        "SELECT series_id, round(gs_cusum_point(pref, tot, t, n), 4) AS c, round(gs_lambda(343, 5, 5, 1), 6) AS lam, "
        "round(gs_sin_theta(array(1D, 0D), array(0.8D, 0.6D)), 6) AS loss FROM gs_prefix WHERE t = 100"
    )


@query("udtf_detect")
def _(spark, sf):
    sqlfuncs.register(spark)
    simulate.noise(spark, 10, 60, reps=3).withColumn("x", F.col("x") + F.when(F.col("t") > 30, 3.0).otherwise(0.0)).createOrReplaceTempView("gs_panel")
    return rounded(spark.sql("SELECT rep, z, stat FROM gs_detect(TABLE(gs_panel) PARTITION BY rep ORDER BY (t, series_id))"), 4, "stat")


# Experiments, with replicates that run in seconds; e1 to e4 plant their changes in the whole events by hour, in orders of the times that are drawn


@query("e1_theory_validation")
def _(spark, sf):
    found = experiments.theory_validation(spark, sizes=(2.0, 4.0), least=(1, 2, 5, 10), reps=4, k=10, panel=panels.event_hour(spark, sf))
    return found.groupBy("config_id").agg(F.round(F.avg("loss"), 4).alias("loss"))


@query("e2_lambda_sweep")
def _(spark, sf):
    found = experiments.lambda_sweep(spark, sizes=(2.0, 4.0), reps=4, panel=panels.event_hour(spark, sf))
    per = found.groupBy("config_id").agg(F.avg("loss").alias("loss"))
    cut = F.substring_index("config_id", "|", 3)
    return rounded(metrics.best_lambda(per.select(cut.alias("config_id"), F.substring_index("config_id", "|", -1).cast("double").alias("multiplier"), "loss")), 4, "loss")


@query("e3_direction_compare")
def _(spark, sf):
    found = experiments.direction_compare(spark, sizes=(1.0, 2.0, 4.0), block=10, step=5, reps=4, panel=panels.event_hour(spark, sf))
    return found.groupBy("config_id", "method").agg(F.round(F.avg("loss"), 4).alias("loss"))


@query("e3_location_compare")
def _(spark, sf):
    found = experiments.location_compare(spark, sizes=(1.0, 2.0), reps=8, panel=panels.event_hour(spark, sf))
    return rounded(metrics.winner_table(metrics.location_error(found, 720)), 4, "mean_abs")


@query("e3_planted_suppliers")
def _(spark, sf):
    found = experiments.planted_compare(panels.supplier_week(spark, sf), supplier_blocks(spark, sf), sizes=(1.0, 2.0), reps=6)
    return rounded(metrics.winner_table(metrics.location_error(found, 356)), 4, "mean_abs")


@query("e4_multi_compare")
def _(spark, sf):
    found = experiments.multi_compare(spark, sparsity=(2,), sizes=(1.0, 2.0), reps=3, intervals=60, nulls=40, panel=panels.event_hour(spark, sf))
    return found.where("method like '%_ari'").groupBy("config_id", "method").agg(F.round(F.avg("loss"), 4).alias("ari"))


def brand_groups(panel: DataFrame) -> DataFrame:
    """The brands' numbers modulo five."""
    return panel.select((F.col("series_id") % 5).alias("group_id"), "series_id").distinct()


@query("e5_real_series")
def _(spark, sf):
    """Log returns of the brands, as they are and with a change planted in two groups halfway; z_true is null where none was planted."""
    panel = relax.work_table(scale.standardised(panels.brand_return(spark, sf)), "returns")
    groups = relax.work_table(brand_groups(panel), "brands")
    z = (panel.agg(F.max("t")).first()[0] or 0) // 2
    planted, _ = panels.plant(panel, groups, [panels.Step(z, CHOSEN, 6.0)])
    out = None
    for name, data, truth in (("observed", panel, None), ("planted", relax.work_table(planted, "planted"), z)):
        found = experiments.real_series(data, groups, INTERVALS, NULLS)
        part = found.select(F.lit(name).alias("panel"), F.lit(truth).cast("long").alias("z_true"), "cp_id", "z", "stat", "depth")
        out = part if out is None else out.unionByName(part)
    return rounded(out, 4, "stat")


@query("e5_group_profile", f"""WITH c AS (SELECT regexp_extract(p_brand, '(\\d+)', 1)::BIGINT AS series_id, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate))::BIGINT AS t,
        sum((l_extendedprice / l_quantity)::DECIMAL(18,4))::DOUBLE / count(*) AS x FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL),
    k AS (SELECT * FROM c WHERE t BETWEEN 1 AND 82 QUALIFY count(*) OVER (PARTITION BY series_id) = 82),
    b AS (SELECT series_id, t, x / lag(x) OVER (PARTITION BY series_id ORDER BY t) AS q FROM k),
    raw AS (SELECT series_id, t - 1 AS t, ln(q) AS x FROM b WHERE q IS NOT NULL),\n{o.SCALE}
    SELECT series_id % 5 AS group_id, t, {r('sqrt(sum(x * x))', 4)} AS norm FROM std GROUP BY ALL""")  # fmt: skip
def _(spark, sf):
    panel = scale.standardised(panels.brand_return(spark, sf))
    return rounded(metrics.group_profile(panel, brand_groups(panel)), 4, "norm")


@query("e6_null_panels")
def _(spark, sf):
    panel = relax.work_table(scale.standardised(panels.supplier_week(spark, sf)), "panel")
    groups = experiments.supplier_groups(spark, sf)
    xi = multi.xi_permuted(panel, groups, reps=NULLS)
    stat = single.detect_single(panel, groups).point
    return stat.select("z", F.round("stat", 4).alias("stat"), F.lit(round(xi, 4)).alias("xi"))


def entry(spark: SparkSession, sf: str = "/root/testdata/sf0.001") -> DataFrame:
    """The flagship: the whole single-change procedure on weekly supplier totals with a planted change, blocks of two."""
    groups = gr.from_table(table(spark, sf, "supplier").select("s_suppkey", F.expr("s_suppkey div 2").alias("g")), "s_suppkey", "g")
    panel, _ = panels.plant(scale.standardised(panels.supplier_week(spark, sf)), groups, [panels.Step(Z, CHOSEN, SIZE)])
    return single.detect_single(relax.work_table(panel, "panel"), groups).point


@query("cost_report")
def _(spark, sf):
    panel, groups, _ = supplier_planted(spark, sf)
    return cost.cost_report(spark, lambda: single.detect_single(panel, groups).point, "single_supplier_week")
