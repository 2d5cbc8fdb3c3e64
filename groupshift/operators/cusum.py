"""CUSUM transforms of long panels: by window, by time buckets, and on intervals from prefix sums."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def cusum_value(pref: Column, tot: Column, t: Column, n: Column) -> Column:
    """The scaled difference of right and left mean at t of n, from the sum up to t and the whole sum."""
    t, n = t.cast("double"), n.cast("double")
    return (t * tot - n * pref) / F.sqrt(n * t * (n - t))


def prefix(panel: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Adds pref (sum of x up to t, with all rows of t if a series has several) and tot, n of each series; one exchange by series serves both."""
    key = Window.partitionBy(*by, "series_id")
    run = key.orderBy("t").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return panel.select(*by, "series_id", "t", F.sum("x").over(run).alias("pref"), F.sum("x").over(key).alias("tot"), F.max("t").over(key).alias("n"))


def cusum(panel: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(series_id, t, cusum) for t = 1..n-1; a panel of one time gives no rows."""
    sums = prefix(panel, by).where("t < n")
    return sums.select(*by, "series_id", "t", cusum_value(F.col("pref"), F.col("tot"), F.col("t"), F.col("n")).alias("cusum"))


def cusum_blocked(panel: DataFrame, bucket: int = 4096, by: tuple[str, ...] = ()) -> DataFrame:
    """The same by two levels: sums within time buckets, and a window over each series' bucket totals.

    A series of any length is sorted bucket by bucket, in as many tasks as it has buckets.
    """
    keys = [*by, "series_id"]
    cut = panel.withColumn("bucket", F.expr(f"(t - 1) div {bucket}"))
    totals = cut.groupBy(*keys, "bucket").agg(F.sum("x").alias("s"), F.max("t").alias("last"))
    whole = Window.partitionBy(*keys)
    before = whole.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(*keys, "bucket", F.coalesce(F.sum("s").over(before), F.lit(0.0)).alias("o"), F.sum("s").over(whole).alias("tot"), F.max("last").over(whole).alias("n"))
    inner = Window.partitionBy(*keys, "bucket").orderBy("t").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    local = cut.withColumn("l", F.sum("x").over(inner)).join(offsets, [*keys, "bucket"]).where("t < n")
    return local.select(*keys, "t", cusum_value(F.col("o") + F.col("l"), F.col("tot"), F.col("t"), F.col("n")).alias("cusum"))


#: Times of a series that one task sorts; longer series go by blocks.
LONG_SERIES = 65_536


def cusum_of(panel: DataFrame, n: int, by: tuple[str, ...] = ()) -> DataFrame:
    """The CUSUM of series of n times: by a window a series, or for long series by blocks of times; the values are the same."""
    return cusum(panel, by) if n <= LONG_SERIES else cusum_blocked(panel, by=by)


def cusum_intervals(panel: DataFrame, intervals: DataFrame, bucket: int = 64) -> DataFrame:
    """(q, series_id, t, cusum) for times s < t < e of each interval (q, s, e], t counted in the whole panel.

    Every interval's CUSUM follows from three values of one prefix table. The range join of times and intervals is
    an equality on time buckets with the bounds checked after.
    """
    sums = prefix(panel).select("series_id", "t", "pref")
    cut = F.expr(f"t div {bucket}")
    spread = intervals.select("q", "s", "e", F.explode(F.sequence(F.expr(f"(s + 1) div {bucket}"), F.expr(f"(e - 1) div {bucket}"))).alias("b")).where("e - s >= 2")
    inner = sums.withColumn("b", cut).join(spread, "b").where("t > s and t < e")
    low = intervals.join(sums, intervals["s"] == sums["t"]).select("q", "series_id", F.col("pref").alias("p_s"))
    high = intervals.join(sums, intervals["e"] == sums["t"]).select("q", "series_id", F.col("pref").alias("p_e"))
    both = inner.join(high, ["q", "series_id"]).join(low, ["q", "series_id"], "left").withColumn("p_s", F.coalesce("p_s", F.lit(0.0)))
    value = cusum_value(F.col("pref") - F.col("p_s"), F.col("p_e") - F.col("p_s"), F.col("t") - F.col("s"), F.col("e") - F.col("s"))
    return both.select("q", "series_id", "t", value.alias("cusum"))
