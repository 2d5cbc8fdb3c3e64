"""Simulated panels: cell by cell from hashes, which any engine can repeat, or in bulk from seeded generators."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from groupshift.operators.intervals import hashed


def uniform(seed: str, *parts: Column) -> Column:
    return (hashed(seed, *parts) + 0.5) / float(2**48)


def normal(seed: str, *parts: Column) -> Column:
    """A standard normal number for the parts' values, from two uniforms."""
    return F.sqrt(-2 * F.log(uniform(f"{seed}:a", *parts))) * F.cos(2 * math.pi * uniform(f"{seed}:b", *parts))


def noise(spark: SparkSession, p: int, n: int, seed: str = "noise", sigma: float = 1.0, reps: int = 1) -> DataFrame:
    """(rep, series_id, t, x): independent normal cells; nothing but a range is read, whatever p and n."""
    cells = spark.range(reps * p * n).select(
        F.expr(f"id div {p * n}").cast("int").alias("rep"), F.expr(f"id % {p * n} div {n} + 1").alias("series_id"), F.expr(f"id % {n} + 1").alias("t")
    )
    return cells.select("rep", "series_id", "t", (normal(seed, F.col("rep"), F.col("series_id"), F.col("t")) * sigma).alias("x"))
