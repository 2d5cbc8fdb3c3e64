"""Reading and writing: the given tables, other formats, panels by time tile, reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"there is no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """parquet, orc, json, csv, text; a schema spares csv and json a pass that infers one."""
    reader = spark.read.format(fmt).options(**options)
    if fmt == "csv":
        reader = reader.option("header", options.get("header", True))
    return (reader.schema(schema) if schema else reader).load(path)


def write_panel(panel: DataFrame, path: str, tile: int = 4096, mode: str = "overwrite") -> None:
    """A panel by time tile, so that intervals of time read whole directories and skip the others."""
    tiled = panel.withColumn("tile_t", F.floor((F.col("t") - 1) / tile).cast("long"))
    tiled.repartition("tile_t").sortWithinPartitions("series_id", "t").write.mode(mode).partitionBy("tile_t").parquet(path)


def read_panel(spark: SparkSession, path: str, first: int | None = None, last: int | None = None, tile: int = 4096) -> DataFrame:
    """Times first..last of a panel that write_panel wrote with the same tile; other tiles are pruned."""
    panel = spark.read.parquet(path)
    if first is not None:
        panel = panel.where((F.col("tile_t") >= (first - 1) // tile) & (F.col("t") >= first))
    if last is not None:
        panel = panel.where((F.col("tile_t") <= (last - 1) // tile) & (F.col("t") <= last))
    return panel.drop("tile_t")


def write_bucketed(panel: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by series: later joins and windows by series need no exchange."""
    panel.write.mode("overwrite").bucketBy(buckets, "series_id").sortBy("series_id", "t").saveAsTable(name)


def write_report(report: DataFrame, path: str, fmt: str = "csv") -> None:
    writer = report.write.mode("overwrite")
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)
