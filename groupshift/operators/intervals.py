"""Random intervals (q, s, e] of 0..n, drawn by hash so that any engine can repeat them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def hashed(seed: str, *parts: Column) -> Column:
    """48 bits of md5 of seed and parts, as a long."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), *[p.cast("string") for p in parts])), 1, 12), 16, 10).cast("long")


def draw_intervals(spark: SparkSession, n: int, count: int, seed: str = "intervals") -> DataFrame:
    """count independent pairs, uniform over 0 <= s, e - s >= 2, e <= n."""
    return draw_for(spark.range(count).select(F.col("id").cast("int").alias("q")), n, seed)


def draw_for(keys: DataFrame, n: int, seed: str = "intervals") -> DataFrame:
    """The pair of each key q, by its hash alone: a number below n (n - 1) / 2 is unranked."""
    k = F.col("k")
    r = F.floor((1 + F.sqrt(1 + 8 * k.cast("double"))) / 2).cast("long")
    # The root is exact to a unit; the neighbours are checked.
    r = F.when(r * (r - 1) / 2 > k, r - 1).when((r + 1) * r / 2 <= k, r + 1).otherwise(r)
    drawn = keys.select("q", F.pmod(hashed(seed, F.col("q")), F.lit(n * (n - 1) // 2)).alias("k"))
    return drawn.withColumn("r", r).select("q", (k - F.expr("r * (r - 1) div 2")).cast("long").alias("s"), (F.col("r") + 1).cast("long").alias("e"))
