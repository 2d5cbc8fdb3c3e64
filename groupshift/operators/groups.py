"""Groupings as bridge tables (group_id, series_id)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def blocks(spark: SparkSession, p: int, size: int, first: int = 0) -> DataFrame:
    """Disjoint blocks of size consecutive ids, from first on."""
    return spark.range(p).select(F.expr(f"id div {size}").cast("long").alias("group_id"), (F.col("id") + first).cast("long").alias("series_id"))


def windows(spark: SparkSession, p: int, size: int, step: int, first: int = 0) -> DataFrame:
    """Windows of size consecutive ids, a step apart, that together cover all ids."""
    starts = list(range(0, max(p - size, 0) + 1, step))
    if starts[-1] + size < p:
        starts.append(p - size)
    rows = spark.createDataFrame(list(enumerate(starts)), "group_id long, start long")
    return rows.select("group_id", F.explode(F.sequence(F.col("start") + first, F.least(F.col("start") + size, F.lit(p)) + first - 1)).alias("series_id"))


def from_table(df: DataFrame, series: str, group: str) -> DataFrame:
    return df.select(F.col(group).cast("long").alias("group_id"), F.col(series).cast("long").alias("series_id")).distinct()


def single(panel: DataFrame) -> DataFrame:
    return panel.select(F.lit(0).cast("long").alias("group_id"), "series_id").distinct()


def singletons(panel: DataFrame) -> DataFrame:
    return panel.select(F.col("series_id").alias("group_id"), "series_id").distinct()


def union(a: DataFrame, b: DataFrame, shift: int = 1_000_000) -> DataFrame:
    """Both groupings, the second's ids shifted."""
    return a.unionByName(b.select((F.col("group_id") + shift).alias("group_id"), "series_id"))


def sizes(groups: DataFrame) -> DataFrame:
    return groups.groupBy("group_id").agg(F.count(F.lit(1)).alias("p_g"))


def uncovered(groups: DataFrame, series: DataFrame) -> DataFrame:
    """Series in no group."""
    return series.select("series_id").distinct().join(groups.select("series_id"), "series_id", "left_anti")


def profile(groups: DataFrame, s: int = 3) -> DataFrame:
    """One row: p, g, least_size, overlap (most groups of one series), sum_sizes, top_s (sum of the s largest), disjoint."""
    per_group = sizes(groups).agg(
        F.count(F.lit(1)).alias("g"), F.min("p_g").alias("least_size"), F.sum("p_g").alias("sum_sizes"),
        F.aggregate(F.slice(F.sort_array(F.collect_list("p_g"), False), 1, s), F.lit(0).cast("long"), lambda a, x: a + x).alias("top_s"),
    )
    per_series = groups.groupBy("series_id").agg(F.count(F.lit(1)).alias("c")).agg(F.count(F.lit(1)).alias("p"), F.max("c").alias("overlap"))
    both = per_group.join(F.broadcast(per_series))
    return both.select("p", "g", "least_size", "overlap", "sum_sizes", "top_s", (F.col("overlap") == 1).alias("disjoint"))


def components(groups: DataFrame) -> DataFrame:
    """series_id, component: series that chains of overlapping groups connect. Groups' ids go to the driver, their members don't."""
    shared = groups.groupBy("series_id").agg(F.sort_array(F.collect_set("group_id")).alias("gs"))
    links = shared.where(F.size("gs") > 1).select(F.explode(F.transform(F.slice("gs", 2, 10**6), lambda x: F.array(F.col("gs")[0], x))).alias("l")).distinct()
    parent: dict[int, int] = {}

    def root(x):
        while parent.get(x, x) != x:
            x = parent[x]
        return x

    for row in links.toLocalIterator():
        a, b = sorted((root(row["l"][0]), root(row["l"][1])))
        parent[b] = a
    named = [(g, root(g)) for g in list(parent)]
    if not named:
        return groups.select("series_id", F.col("group_id").alias("component")).distinct()
    spark = groups.sparkSession
    found = groups.join(F.broadcast(spark.createDataFrame(named, "group_id long, r long")), "group_id", "left")
    return found.select("series_id", F.coalesce("r", "group_id").alias("component")).distinct()
