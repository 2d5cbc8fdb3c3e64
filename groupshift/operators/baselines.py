"""Competing detectors, from a CUSUM table (series_id, t, cusum) to (z, stat)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupshift.functions import tuning

from . import direction as di
from . import locate as lo
from . import relax


def l2(c: DataFrame) -> DataFrame:
    return lo.peak(c.groupBy("t").agg(F.sqrt(F.sum(F.col("cusum") * F.col("cusum"))).alias("s")), "s")


def linf(c: DataFrame) -> DataFrame:
    return lo.peak(c.groupBy("t").agg(F.max(F.abs("cusum")).alias("s")), "s")


def _ranked(c: DataFrame) -> DataFrame:
    """Sizes at each time in falling order: m, their running sum and square sum, the whole sum and p."""
    key = Window.partitionBy("t")
    down = key.orderBy(F.desc("a"), "series_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = c.select("series_id", "t", F.abs("cusum").alias("a"))
    return rows.select(
        "t", F.row_number().over(key.orderBy(F.desc("a"), "series_id")).alias("m"), F.sum("a").over(down).alias("top"),
        F.sum(F.col("a") * F.col("a")).over(down).alias("top2"), F.sum("a").over(key).alias("whole"), F.count(F.lit(1)).over(key).alias("p"),
    )


def double_cusum(c: DataFrame, power: float = 0.5) -> DataFrame:
    """Over m and t: the mean of the m largest sizes less the rest's sum over 2p - m, weighted by (m (2p - m) / 2p) ** power."""
    m, p = F.col("m").cast("double"), F.col("p").cast("double")
    value = F.pow(m * (2 * p - m) / (2 * p), F.lit(power)) * (F.col("top") / m - (F.col("whole") - F.col("top")) / (2 * p - m))
    return lo.peak(_ranked(c).groupBy("t").agg(F.max(value).alias("s")), "s")


def scan(c: DataFrame) -> DataFrame:
    """Over m and t: the sum of the m largest squares, less m, over sqrt(2 m)."""
    m = F.col("m").cast("double")
    return lo.peak(_ranked(c).groupBy("t").agg(F.max((F.col("top2") - m) / F.sqrt(2 * m)).alias("s")), "s")


def sparsified(c: DataFrame, level: float) -> DataFrame:
    """Sums of the sizes above a level."""
    return lo.peak(c.where(F.abs("cusum") > level).groupBy("t").agg(F.sum(F.abs("cusum")).alias("s")), "s")


def componentwise(c: DataFrame) -> DataFrame:
    """(series_id, z, stat): each series by itself."""
    best = F.max(F.struct(F.abs("cusum").alias("stat"), (-F.col("t")).alias("back")))
    return c.groupBy("series_id").agg(best.alias("b")).select("series_id", (-F.col("b.back")).alias("z"), F.col("b.stat").alias("stat"))


def soft_threshold(c: DataFrame, lam: float) -> DataFrame:
    """(series_id, t, m): entries pulled towards 0 by lam; zeros are left out."""
    return c.where(F.abs("cusum") > lam).select("series_id", "t", (F.signum("cusum") * (F.abs("cusum") - lam)).alias("m"))


def sparse_projection(c: DataFrame, lam: float | None = None, method: str = "auto") -> tuple[DataFrame, DataFrame]:
    """((z, stat), direction) of the projection detector without groups."""
    if lam is None:
        r = c.agg(F.countDistinct("series_id").alias("p"), F.max("t").alias("n")).first()
        lam = tuning.lambda_sparse(r["p"], r["n"] + 1)
    v = di.leading_left(relax.work_table(relax.columns_of(soft_threshold(c, lam), "m"), "thresholded"), method)
    return lo.locate(v, c), v


def oracle(c: DataFrame, truth: DataFrame) -> DataFrame:
    """Projection on the true direction (series_id, theta)."""
    size = truth.agg(F.sqrt(F.sum(F.col("theta") * F.col("theta")))).first()[0]
    return lo.locate(truth.select("series_id", (F.col("theta") / size).alias("v")), c)


def all_located(c: DataFrame, level: float) -> DataFrame:
    """(method, z, stat) of the aggregating detectors."""
    found = {"l2": l2(c), "linf": linf(c), "double_cusum": double_cusum(c), "scan": scan(c), "sparsified": sparsified(c, level)}
    out = None
    for name, df in found.items():
        part = df.select(F.lit(name).alias("method"), "z", "stat")
        out = part if out is None else out.unionByName(part)
    return out


__all__ = ["all_located", "componentwise", "double_cusum", "l2", "linf", "oracle", "scan", "soft_threshold", "sparse_projection", "sparsified"]
