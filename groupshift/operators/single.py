"""Single change points: the whole procedure, with and without sample splitting."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupshift.functions import tuning

from . import cusum as cu
from . import direction as di
from . import groups as gr
from . import locate as lo
from . import relax


@dataclass(frozen=True)
class Found:
    point: DataFrame  # z, stat
    direction: DataFrame  # series_id, v
    lam: float


def level(panel: DataFrame, groups: DataFrame, lam: float | None) -> tuple[float, bool, int]:
    """(lambda, whether groups are disjoint, n); lambda is the practical one where none is given."""
    profile = gr.profile(groups).first()
    n = panel.agg(F.max("t")).first()[0] or 0
    if lam is None:
        lam = tuning.lambda_practical(max(n, 2), profile["g"], profile["least_size"])
    return lam, bool(profile["disjoint"]), n


def solved(c: DataFrame, groups: DataFrame, lam: float, solver: str, disjoint: bool) -> DataFrame:
    """Column blocks (t, ids, vec) of the relaxed solution. Its length does not bear on the direction and is left as it is."""
    if solver == "auto":
        solver = "closed" if disjoint else "columnwise"
    if solver == "closed":
        return relax.shrink_blocks(relax.to_blocks(c, groups), lam).groupBy("t").agg(
            F.flatten(F.collect_list("ids")).alias("ids"), F.flatten(F.collect_list("vec")).alias("vec")
        )
    columns = relax.columns_of(c)
    if solver == "iterative":
        return relax.conditional_gradient(relax.work_table(columns, "columns"), groups, lam)
    return relax.columnwise_dual(columns, groups, lam)


def detect_single(panel: DataFrame, groups: DataFrame, lam: float | None = None, solver: str = "auto", method: str = "auto") -> Found:
    """(z, stat) and the direction. The panel is expected to be standardised.

    solver: closed (disjoint groups), columnwise (exact for any groups, one pass) or iterative; auto takes the
    closed form for disjoint groups. If every block is shrunk to zero there is no direction, z is null and stat 0.
    """
    lam, disjoint, n = level(panel, groups, lam)
    c = relax.work_table(cu.cusum_of(panel, n), "cusum")
    m = relax.work_table(solved(c, groups, lam, solver, disjoint), "relaxed")
    v = di.leading_left(m, method)
    return Found(lo.locate(v, c), v, lam)


def detect_single_split(panel: DataFrame, groups: DataFrame, lam: float | None = None, solver: str = "auto", method: str = "auto") -> Found:
    """Odd times give the direction and even times the place; lambda is that of the whole length. An odd last time is left out."""
    lam, disjoint, n = level(panel, groups, lam)
    halves = panel.where(F.col("t") <= n // 2 * 2).select(
        (F.col("t") % 2).cast("int").alias("half"), "series_id", F.expr("(t + 1) div 2").alias("t"), "x"
    )
    c = relax.work_table(cu.cusum_of(halves, n // 2, by=("half",)), "cusum")
    odd, even = c.where("half = 1").drop("half"), c.where("half = 0").drop("half")
    v = di.leading_left(relax.work_table(solved(odd, groups, lam, solver, disjoint), "relaxed"), method)
    point = lo.locate(v, even).select((F.col("z") * 2).alias("z"), "stat")
    return Found(point, v, lam)
