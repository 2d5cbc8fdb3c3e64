"""Accuracy measures over directions, locations, segmentations and runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def sin_theta(found: DataFrame, truth: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Sine of the angle between two directions (series_id, v); each is brought to unit length, missing entries are 0."""
    a = found.select(*by, "series_id", F.col("v").alias("a"))
    b = truth.select(*by, "series_id", F.col("v").alias("b"))
    both = a.join(b, [*by, "series_id"], "full")
    x, y = F.coalesce("a", F.lit(0.0)), F.coalesce("b", F.lit(0.0))
    sums = both.groupBy(*by).agg(F.sum(x * y).alias("ab"), F.sum(x * x).alias("aa"), F.sum(y * y).alias("bb"))
    cosine2 = F.coalesce(F.try_divide(F.col("ab") * F.col("ab"), F.col("aa") * F.col("bb")), F.lit(0.0))
    return sums.select(*by, F.sqrt(F.greatest(1 - cosine2, F.lit(0.0))).alias("loss"))


def location_error(runs: DataFrame, n: int) -> DataFrame:
    """Mean |z_hat - z| and the same over n, by config_id and method; a run that found nothing counts as found at 0."""
    off = F.abs(F.coalesce("z_hat", F.lit(0)) - F.col("z_true"))
    return runs.groupBy("config_id", "method").agg(F.avg(off).alias("mean_abs"), (F.avg(off) / n).alias("mean_share"), F.count(F.lit(1)).alias("runs"))


def segments(points: DataFrame, n: int) -> DataFrame:
    """(config_id, lo, hi] between the points (config_id, z) of each configuration, which all must have a row for z = n."""
    before = F.lag("z", 1, 0).over(Window.partitionBy("config_id").orderBy("z"))
    inside = points.where(F.col("z").between(1, n)).distinct()
    return inside.select("config_id", before.alias("lo"), F.col("z").alias("hi"))


def ari(truth: DataFrame, found: DataFrame, n: int) -> DataFrame:
    """(config_id, ari) of the segmentations of 1..n given by points (config_id, z).

    Segments meet segments, never times: overlaps of intervals within a configuration.
    """
    configs = truth.select("config_id").distinct()
    ends = configs.select("config_id", F.lit(n).cast("long").alias("z"))
    a = segments(truth.select("config_id", "z").unionByName(ends), n)
    b = segments(found.select("config_id", "z").unionByName(ends), n)
    pairs = lambda k: k * (k - 1) / 2.0
    size = F.least(a["hi"], b["hi"]) - F.greatest(a["lo"], b["lo"])
    cells = a.join(b, (a["config_id"] == b["config_id"]) & (a["lo"] < b["hi"]) & (b["lo"] < a["hi"]))
    common = cells.groupBy(a["config_id"].alias("config_id")).agg(F.sum(pairs(size)).alias("c"))
    first = a.groupBy("config_id").agg(F.sum(pairs(F.col("hi") - F.col("lo"))).alias("x"))
    second = b.groupBy("config_id").agg(F.sum(pairs(F.col("hi") - F.col("lo"))).alias("y"))
    expected, most = F.col("x") * F.col("y") / (n * (n - 1) / 2.0), (F.col("x") + F.col("y")) / 2.0
    value = F.when(most == expected, 1.0).otherwise((F.col("c") - expected) / (most - expected))
    return common.join(first, "config_id").join(second, "config_id").select("config_id", value.alias("ari"))


def location_histogram(runs: DataFrame, width: int) -> DataFrame:
    """(method, bin, n): how often each stretch of width times was found."""
    return runs.where("z_hat is not null").groupBy("method", F.expr(f"(z_hat - 1) div {width}").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def group_profile(panel: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, t, norm): l2 norm of the data of each group over time."""
    return groups.join(panel, "series_id").groupBy("group_id", "t").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))


def loglog_slope(curve: DataFrame, x: str, y: str, by: tuple[str, ...] = ()) -> DataFrame:
    return curve.groupBy(*by).agg(F.regr_slope(F.log(F.col(y)), F.log(F.col(x))).alias("slope"))


def best_lambda(sweep: DataFrame) -> DataFrame:
    """(config_id, multiplier, loss): the multiplier of least loss, the smallest of equal ones."""
    best = F.min(F.struct("loss", "multiplier")).alias("b")
    return sweep.groupBy("config_id").agg(best).select("config_id", F.col("b.multiplier").alias("multiplier"), F.col("b.loss").alias("loss"))


def winner_table(errors: DataFrame) -> DataFrame:
    """(config_id, method, mean_abs, place): methods in order of error; equal errors share a place."""
    order = Window.partitionBy("config_id").orderBy("mean_abs")
    return errors.select("config_id", "method", "mean_abs", F.rank().over(order).alias("place"))


def null_exceedance(stats: DataFrame, level: float, bound: float) -> DataFrame:
    return stats.agg(F.avg((F.col("stat") > level).cast("double")).alias("rate"), F.lit(bound).alias("bound"))
