"""Robust row scales from successive differences."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def differences(panel: DataFrame) -> DataFrame:
    before = F.lag("x").over(Window.partitionBy("series_id").orderBy("t"))
    return panel.select("series_id", "t", (F.col("x") - before).alias("d")).where("d is not null")


def row_scale(panel: DataFrame, kind: str = "mean_ad") -> DataFrame:
    """(series_id, sigma): mean or median absolute deviation of the differences, consistent for normal noise."""
    d, key = differences(panel), Window.partitionBy("series_id")
    if kind == "mean_ad":
        off = d.select("series_id", F.abs(F.col("d") - F.avg("d").over(key)).alias("a"))
        return off.groupBy("series_id").agg((F.avg("a") * (math.sqrt(math.pi) / 2)).alias("sigma"))
    middle = d.groupBy("series_id").agg(F.expr("percentile(d, 0.5)").alias("m"))
    off = d.join(middle, "series_id").select("series_id", F.abs(F.col("d") - F.col("m")).alias("a"))
    return off.groupBy("series_id").agg((F.expr("percentile(a, 0.5)") * (1.4826 / math.sqrt(2))).alias("sigma"))


def standardise(panel: DataFrame, scale: DataFrame) -> DataFrame:
    """Rows divided by their scale; a series without variation becomes zero."""
    value = F.coalesce(F.col("x") / F.nullif(F.col("sigma"), F.lit(0.0)), F.lit(0.0))
    return panel.join(scale, "series_id").select("series_id", "t", value.alias("x"))


def standardised(panel: DataFrame, kind: str = "mean_ad") -> DataFrame:
    return standardise(panel, row_scale(panel, kind))
