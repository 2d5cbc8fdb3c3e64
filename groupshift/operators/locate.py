"""Projection on a direction (series_id, v), and the peak of what is projected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .cusum import cusum


def projected(direction: DataFrame, m: DataFrame, value: str) -> DataFrame:
    """(t, proj): the direction is one number a series; Spark broadcasts it where its size allows."""
    return m.join(direction, "series_id").groupBy("t").agg(F.sum(F.col("v") * F.col(value)).alias("proj"))


def peak(curve: DataFrame, value: str) -> DataFrame:
    """(z, stat): the time of the largest value, the earliest of equal ones. An empty or zero curve gives a null z and 0."""
    best = curve.agg(F.max(F.struct(F.col(value).alias("stat"), (-F.col("t")).alias("back"))).alias("best"))
    stat = F.coalesce(F.col("best.stat"), F.lit(0.0))
    return best.select(F.when(stat > 0, -F.col("best.back")).alias("z"), stat.alias("stat"))


def locate(direction: DataFrame, m: DataFrame, on: str = "cusum") -> DataFrame:
    """(z, stat). on='data' projects the panel first and takes one series' CUSUM, which is the same by linearity."""
    if on == "data":
        line = projected(direction, m, "x").select(F.lit(0).cast("long").alias("series_id"), "t", F.col("proj").alias("x"))
        curve = cusum(line).select("t", F.col("cusum").alias("proj"))
    else:
        curve = projected(direction, m, "cusum")
    return peak(curve.select("t", F.abs("proj").alias("size")), "size")
