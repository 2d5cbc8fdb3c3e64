"""Several change points: random intervals searched once, then recursion on the table of candidates."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from groupshift import kernels

from . import relax
from . import cusum as cu
from . import wide
from .direction import GRAM_TIMES
from .intervals import draw_intervals
from .single import level

#: Up to so many cells a panel goes to every executor whole (160 MB of doubles), and each interval is one row of work.
REPLICATED_CELLS = 20_000_000
#: Up to so many cells it does where its times are permuted; with more, and few times, it is dealt to slices if the detector has that form.
PERMUTED_CELLS = 2_000_000
CANDIDATE = "q int, s long, e long, b long, stat double"
#: Statistics of the distributed mode: directions by power steps, and curves over whole columns.
DIRECTIONS, CURVES = ("gsp", "gsp_columnwise", "sparse_projection"), ("l2", "linf", "double_cusum", "scan", "sparsified")
#: Up to so many entries that are not zero an interval's direction is found in one task; beyond it, by power steps as joins.
LOCAL_CELLS = 4_000_000


def as_matrix(panel: DataFrame, most: int = REPLICATED_CELLS):
    """(matrix, series ids) on the driver, for a panel of at most so many cells."""
    import numpy as np

    cells = panel.count()
    if cells > most:
        raise ValueError(f"{cells} cells are more than {most}: use the distributed mode")
    pdf = panel.toPandas().pivot(index="series_id", columns="t", values="x").sort_index(axis=0).sort_index(axis=1)
    return pdf.to_numpy(dtype=float), np.array(pdf.index)


def as_rows(groups: DataFrame, ids) -> list:
    """The groups as arrays of row numbers among ids."""
    import numpy as np

    place = {int(s): i for i, s in enumerate(ids)}
    return [np.array([place[s] for s in members if s in place]) for members in relax.membership(groups).values()]


def finder(stat: str, groups, lam: float) -> Callable:
    return lambda x: kernels.method(x, stat, groups, lam)


def interval_candidates(
    panel: DataFrame, groups: DataFrame, intervals: DataFrame, lam: float | None = None, stat: str = "gsp", mode: str = "auto", steps: int = 1000
) -> DataFrame:
    """(q, s, e, b, stat) of the detector on (s, e] for each interval; b counts in the whole panel.

    replicated: the panel goes to every executor and intervals are dealt out. distributed: all intervals advance
    together from one table of prefix sums, with the same result; gsp with overlapping groups and gsp_split raise an
    error there (gsp_columnwise takes any groups), and so do power steps that have not converged after so many steps.
    auto goes by the panel's size.
    """
    lam, disjoint, _ = level(panel, groups, lam)
    if mode == "auto":
        mode = "replicated" if panel.count() <= REPLICATED_CELLS else "distributed"
    if mode == "distributed":
        if stat not in DIRECTIONS + CURVES or (stat == "gsp" and not disjoint):
            raise ValueError(f"the distributed mode has no {stat}" + (" for overlapping groups: use gsp_columnwise" if stat == "gsp" else ""))
        c = relax.work_table(cu.cusum_intervals(panel, intervals), "interval_cusum")
        return _distributed(c, groups, intervals, lam, stat, steps)
    x, ids = as_matrix(panel)
    rows = as_rows(groups, ids)
    spark = panel.sparkSession
    shared = spark.sparkContext.broadcast((x, rows))

    def run(batches):
        import pandas as pd

        x, rows = shared.value
        find = finder(stat, rows, lam)
        for pdf in batches:
            found = kernels.interval_candidates(x, zip(pdf["s"], pdf["e"], strict=True), find)
            out = pd.DataFrame(found, columns=["s", "e", "b", "stat"])
            out.insert(0, "q", pdf["q"].to_numpy())
            yield out.astype({"b": "Int64"})

    return intervals.repartition(spark.sparkContext.defaultParallelism).mapInPandas(run, CANDIDATE)


def _columns(c: DataFrame) -> DataFrame:
    """Whole columns (t, ids, vec) of all intervals, t standing for both: q * 2^40 + t."""
    return relax.columns_of(c.select((F.col("q").cast("long") * (1 << 40) + F.col("t")).alias("t"), "series_id", "cusum"))


#: The two numbers in it.
_Q, _T = "int(t div 1099511627776) AS q", "t % 1099511627776 AS t"


def _curve(c: DataFrame, intervals: DataFrame, stat: str) -> DataFrame:
    """(q, t, size) of a statistic of each column."""
    if stat in ("l2", "linf"):
        size = F.sqrt(F.sum(F.col("cusum") * F.col("cusum"))) if stat == "l2" else F.max(F.abs("cusum"))
        return c.groupBy("q", "t").agg(size.alias("size"))
    columns = _columns(c)
    if stat == "sparsified":
        a = F.abs("cusum")
        level = F.sqrt(2 * F.log(F.greatest(F.lit(2), F.col("p") * (F.col("e") - F.col("s")))))
        cut = c.join(intervals.select("q", "s", "e"), "q").crossJoin(c.agg(F.countDistinct("series_id").alias("p")))
        return cut.groupBy("q", "t").agg(F.sum(F.when(a > level, a).otherwise(0.0)).alias("size"))

    def run(batches):
        import numpy as np

        for batch in batches:
            if len(batch):
                yield batch[["t"]].assign(size=getattr(kernels, stat)(np.array(batch["vec"].tolist()).T))

    return columns.mapInPandas(run, "t long, size double").selectExpr(_Q, _T, "size")


def _relaxed(c: DataFrame, groups: DataFrame, intervals: DataFrame, lam: float, stat: str) -> DataFrame:
    """(q, series_id, t, m): what is left of each interval's CUSUM, without zero entries."""
    if stat == "sparse_projection":
        p = c.agg(F.countDistinct("series_id").alias("p"))
        cut = c.join(intervals.select("q", "s", "e"), "q").crossJoin(p).withColumn("l", F.sqrt(F.log(F.col("p") * F.log(F.col("e") - F.col("s"))) / 2))
        return cut.where("abs(cusum) > l").select("q", "series_id", "t", (F.signum("cusum") * (F.abs("cusum") - F.col("l"))).alias("m"))
    if stat == "gsp_columnwise":
        long = relax.to_long(relax.columnwise_dual(_columns(c), groups, lam))
        return long.where("m != 0").selectExpr(_Q, "series_id", _T, "m")
    joined = c.join(relax.sized_groups(groups), "series_id")
    norms = joined.groupBy("q", "group_id", "t").agg(F.sqrt(F.sum(F.col("cusum") * F.col("cusum"))).alias("norm"), F.first("p_g").alias("p_g"))
    norms = norms.where(F.col("norm") > lam * F.sqrt("p_g")).select("q", "group_id", "t", (1 - lam * F.sqrt("p_g") / F.col("norm")).alias("f"))
    return joined.join(norms, ["q", "group_id", "t"]).select("q", "series_id", "t", (F.col("cusum") * F.col("f")).alias("m"))


def _exact_directions(m: DataFrame) -> DataFrame:
    def run(key, pdf):
        import numpy as np
        import pandas as pd

        ids, rows = np.unique(pdf["series_id"].to_numpy(), return_inverse=True)
        times, columns = np.unique(pdf["t"].to_numpy(), return_inverse=True)
        x = np.zeros((len(ids), len(times)))
        x[rows, columns] = pdf["m"].to_numpy()
        return pd.DataFrame({"q": key[0], "series_id": ids, "v": kernels.leading_left(x)})

    return m.groupBy("q").applyInPandas(run, "q int, series_id long, v double")


def _power_directions(m: DataFrame, steps: int, tol: float = 1e-6) -> DataFrame:
    """Power steps for all intervals at once, as joins and sums keyed by interval, until a step moves no direction by more than tol."""
    v = m.select("q", "series_id").distinct()
    v = v.withColumn("v", 1 / F.sqrt(F.count(F.lit(1)).over(Window.partitionBy("q"))))
    for k in range(steps):
        last = v
        w = m.join(v, ["q", "series_id"]).groupBy("q", "t").agg(F.sum(F.col("m") * F.col("v")).alias("w"))
        v = m.join(w, ["q", "t"]).groupBy("q", "series_id").agg(F.sum(F.col("m") * F.col("w")).alias("v"))
        size = v.groupBy("q").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("size"))
        v = v.join(size, "q").select("q", "series_id", (F.col("v") / F.nullif("size", F.lit(0.0))).alias("v"))
        if k % 4 == 3 or k == steps - 1:
            # the step before is kept beside the new one, so that the last move can be measured
            both = relax.work_table(v.join(last.withColumnRenamed("v", "before"), ["q", "series_id"]), "interval_directions")
            v = both.select("q", "series_id", "v")
            moved = both.groupBy("q").agg(F.sqrt(F.sum((F.col("v") - F.col("before")) ** 2)).alias("moved")).where(F.col("moved").isNull() | (F.col("moved") > tol))
            if moved.isEmpty():
                return v
    raise RuntimeError(f"the directions of {moved.count()} intervals still move after {steps} power steps")


def _directions(m: DataFrame, steps: int) -> DataFrame:
    """(q, series_id, v) for every interval with an entry; both ways lead to the leading left singular vector."""
    cells = m.groupBy("q").agg(F.count(F.lit(1)).alias("cells")).persist()
    large = cells.where(F.col("cells") > LOCAL_CELLS).select("q")
    if large.isEmpty():
        return _exact_directions(m)
    found = _power_directions(relax.work_table(m.join(large, "q", "left_semi"), "interval_large"), steps)
    return found.unionByName(_exact_directions(m.join(large, "q", "left_anti")))


def _distributed(c: DataFrame, groups: DataFrame, intervals: DataFrame, lam: float, stat: str, steps: int) -> DataFrame:
    if stat in CURVES:
        curve = _curve(c, intervals, stat)
    else:
        m = relax.work_table(_relaxed(c, groups, intervals, lam, stat), "interval_shrunk")
        curve = c.join(_directions(m, steps), ["q", "series_id"]).groupBy("q", "t").agg(F.abs(F.sum(F.col("cusum") * F.col("v"))).alias("size"))
    best = curve.groupBy("q").agg(F.max(F.struct(F.col("size").alias("stat"), (-F.col("t")).alias("back"))).alias("x"), F.max(F.abs("size")).alias("any"))
    found = intervals.join(best.where("any > 0"), "q", "left")
    return found.select("q", "s", "e", (-F.col("x.back")).alias("b"), F.coalesce("x.stat", F.lit(0.0)).alias("stat"))


def recurse(candidates: DataFrame, n: int, threshold: float) -> DataFrame:
    """(cp_id, z, stat, depth, q): the strongest interval inside the current segment, split there if it reaches the threshold.

    The table has a row for each interval drawn, a number that the caller chooses; it goes to the driver.
    """
    rows = sorted(tuple(r) for r in candidates.select("q", "s", "e", "b", "stat").collect())
    found = kernels.recurse([(s, e, b, stat) for _, s, e, b, stat in rows], n, threshold)
    out = [(i, z, stat, depth, rows[at][0]) for i, (z, stat, depth, at) in enumerate(found)]
    return candidates.sparkSession.createDataFrame(out, "cp_id int, z long, stat double, depth int, q int")


def detect_multiple(
    panel: DataFrame, groups: DataFrame, threshold: float, lam: float | None = None, intervals: DataFrame | int | str = 200, seed: str = "intervals", stat: str = "gsp", mode: str = "auto"
) -> DataFrame:
    """The points found. intervals is a number to draw, a table (q, s, e), or 'segment' for plain top-down segmentation."""
    lam, _, n = level(panel, groups, lam)
    if isinstance(intervals, str):
        x, ids = as_matrix(panel)
        found = kernels.top_down(x, finder(stat, as_rows(groups, ids), lam), threshold)
        rows = [(i, z, s, depth, None) for i, (z, s, depth) in enumerate(found)]
        return panel.sparkSession.createDataFrame(rows, "cp_id int, z long, stat double, depth int, q int")
    if isinstance(intervals, int):
        intervals = draw_intervals(panel.sparkSession, n, intervals, seed)
    return recurse(interval_candidates(panel, groups, intervals, lam, stat, mode), n, threshold)


def xi_monte_carlo(spark: SparkSession, p: int, n: int, groups: list, lam: float, reps: int = 1000, stat: str = "gsp", quantile: float | None = None, seed: int = 1) -> float:
    """The largest statistic (or a quantile) over change-free normal panels; replicates are dealt out."""

    def run(batches):
        for pdf in batches:
            values = [kernels.method(kernels.gaussian(p, n, [], seed * 1_000_003 + int(r)), stat, groups, lam)[1] for r in pdf["id"]]
            yield pdf.assign(stat=values)[["stat"]]

    found = spark.range(reps).repartition(min(reps, 4 * spark.sparkContext.defaultParallelism)).mapInPandas(run, "stat double")
    return found.agg(F.max("stat") if quantile is None else F.percentile("stat", F.lit(quantile))).first()[0]


def _order(seed: int, r: int, n: int):
    import numpy as np

    return np.random.default_rng(seed * 1_000_003 + r).permutation(n)


def xi_permuted(panel: DataFrame, groups: DataFrame, lam: float | None = None, reps: int = 100, stat: str = "gsp", quantile: float | None = None, seed: int = 1) -> float:
    """The same over joint permutations of a panel's times, which keep what series share at a time and undo any change.

    A panel beyond REPLICATED_CELLS is dealt to slices of series, for the detectors of wide.METHODS; gsp needs disjoint groups there.
    One of at most GRAM_TIMES times is from PERMUTED_CELLS on, where that is possible.
    """
    lam, disjoint, n = level(panel, groups, lam)
    spark = panel.sparkSession
    largest = F.max("stat") if quantile is None else F.percentile("stat", F.lit(quantile))
    sliced = stat in wide.METHODS and (stat != "gsp" or disjoint) and n <= GRAM_TIMES
    if panel.count() > (min(PERMUTED_CELLS, REPLICATED_CELLS) if sliced else REPLICATED_CELLS):
        if stat == "gsp" and not disjoint:
            raise ValueError("a panel dealt to slices has no gsp for overlapping groups")
        orders = [(_order(seed, r, n), None, (), 0.0) for r in range(reps)]
        return wide.detect_orders(panel, groups, orders, lam, (stat,)).agg(largest).first()[0]
    x, ids = as_matrix(panel)
    shared = spark.sparkContext.broadcast((x, as_rows(groups, ids)))

    def run(batches):
        x, rows = shared.value
        for pdf in batches:
            values = [kernels.method(x[:, _order(seed, int(r), x.shape[1])], stat, rows, lam)[1] for r in pdf["id"]]
            yield pdf.assign(stat=values)[["stat"]]

    found = spark.range(reps).repartition(min(reps, 4 * spark.sparkContext.defaultParallelism)).mapInPandas(run, "stat double")
    return found.agg(largest).first()[0]


__all__ = ["as_matrix", "as_rows", "detect_multiple", "interval_candidates", "recurse", "xi_monte_carlo", "xi_permuted"]
