"""Relational operators around the detectors: segments, range joins, top-k, agreement, subtotals, time buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupshift.sources.work import work_table


def asof_segment(times: DataFrame, changes: DataFrame) -> DataFrame:
    """Adds segment: how many changes z lie before t. The changes, few beside the times, are one array on one broadcast row."""
    marks = changes.agg(F.sort_array(F.collect_set("z")).alias("_z"))
    before = F.size(F.filter("_z", lambda z: z < F.col("t")))
    return times.join(F.broadcast(marks)).withColumn("segment", before.cast("int")).drop("_z")


def numbered(df: DataFrame, order: str, name: str = "t") -> DataFrame:
    """Adds the 1-based place of each row in the order of a column without ties, by ranges instead of one sorted task."""
    dealt = work_table(df.repartitionByRange(F.col(order)).withColumn("_p", F.spark_partition_id()), "ranges")
    offsets = dealt.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"))  # a row for each range
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = offsets.select("_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_o"))
    inner = F.row_number().over(Window.partitionBy("_p").orderBy(order))
    return dealt.withColumn("_r", inner).join(offsets, "_p").withColumn(name, (F.col("_o") + F.col("_r")).cast("long")).drop("_p", "_r", "_o")


def segment_means(panel: DataFrame, changes: DataFrame) -> DataFrame:
    """(series_id, segment, mean, n): the piecewise constant means between changes."""
    return asof_segment(panel, changes).groupBy("series_id", "segment").agg(F.avg("x").alias("mean"), F.count(F.lit(1)).alias("n"))


def jump_vectors(panel: DataFrame, changes: DataFrame) -> DataFrame:
    """(cp_id, series_id, v): estimated jump of each series at each change."""
    before = F.lag("mean").over(Window.partitionBy("series_id").orderBy("segment"))
    means = segment_means(panel, changes).withColumn("before", before).where("before is not null")
    return means.select((F.col("segment") - 1).alias("cp_id"), "series_id", (F.col("mean") - F.col("before")).alias("v"))


def range_join(points: DataFrame, intervals: DataFrame, bucket: int) -> DataFrame:
    """points (t, ..) with the intervals (q, s, e] that hold them: equality on buckets, bounds checked after."""
    spread = intervals.select("q", "s", "e", F.explode(F.sequence(F.expr(f"(s + 1) div {bucket}"), F.expr(f"e div {bucket}"))).alias("_b"))
    return points.withColumn("_b", F.expr(f"t div {bucket}")).join(spread, "_b").where("t > s and t <= e").drop("_b")


def topk(df: DataFrame, key: list[str], k: int, by: str, tie: str = "t") -> DataFrame:
    """The k rows of each key with the largest by; ties go to the smallest tie."""
    order = Window.partitionBy(*key).orderBy(F.desc(by), tie)
    return df.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def common(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("z").intersect(b.select("z"))


def only_in(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("z").exceptAll(b.select("z"))


def either(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("z").union(b.select("z")).distinct()


def subtotals(df: DataFrame, dims: list[str], value: str, how: str = "rollup") -> DataFrame:
    """Sums and counts by dims and their subtotals (rollup or cube); level is Spark's grouping id."""
    grouped = df.rollup(*dims) if how == "rollup" else df.cube(*dims)
    return grouped.agg(F.grouping_id().cast("int").alias("level"), F.sum(value).alias("total"), F.count(F.lit(1)).alias("n"))


def grouping_sets(df: DataFrame, sets: list[list[str]], value: str) -> DataFrame:
    dims = list(dict.fromkeys(d for s in sets for d in s))
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *dims).agg(F.sum(value).alias("total"))


def bucket_time(df: DataFrame, column: str, anchor: str, days: int) -> DataFrame:
    return df.withColumn("t", (F.floor(F.datediff(F.col(column), F.lit(anchor).cast("date")) / days) + 1).cast("long"))


def rank_blocks(norms: DataFrame) -> DataFrame:
    """Groups ranked by their norm at each time: row number, rank, dense rank and quarter."""
    order = Window.partitionBy("t").orderBy(F.desc("norm"), "group_id")
    ties = Window.partitionBy("t").orderBy(F.desc("norm"))
    return norms.select("group_id", "t", "norm", F.row_number().over(order).alias("rn"), F.rank().over(ties).alias("rk"), F.dense_rank().over(ties).alias("dr"), F.ntile(4).over(order).alias("quarter"))
