"""A stream of events as panel cells, and detection as time goes on."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(folder)


def hourly_cells(events: DataFrame, late: str = "2 hours", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(hour, event_type, bucket, n, total) of closed windows; events later than the watermark allows are dropped by Spark and counted."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    window = F.window("at", width, slide) if slide else F.window("at", width)
    cells = timed.groupBy(window.alias("w"), "event_type", F.pmod("user_id", F.lit(10)).alias("bucket"))
    return cells.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("value").cast("decimal(18,4)")).alias("total")).select(F.col("w.start").alias("hour"), "event_type", "bucket", "n", "total")


def bursts(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Sessions of each user: (user_id, start, end, n)."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    grouped = timed.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def running_scale(cells: DataFrame) -> DataFrame:
    """(series, hour, count, prefix, scale) as cells of each series arrive: state is four numbers a series.

    cells is a stream (series long, hour timestamp, x double), each hour of a series once. A series' cells are taken
    in order of hour within a trigger. scale is the mean absolute difference of successive values so far.
    """

    def update(key, batches, state):
        import pandas as pd

        count, total, last, moved = state.get if state.exists else (0, 0.0, 0.0, 0.0)
        rows = pd.concat(list(batches)).sort_values("hour")
        out = []
        for hour, x in zip(rows["hour"], rows["x"], strict=True):
            moved += abs(x - last) if count else 0.0
            count, total, last = count + 1, total + x, x
            out.append((key[0], hour, count, total, moved / max(1, count - 1)))
        state.update((count, total, last, moved))
        yield pd.DataFrame(out, columns=["series", "hour", "count", "prefix", "scale"])

    return cells.groupBy("series").applyInPandasWithState(
        update, "series long, hour timestamp, count long, prefix double, scale double", "count long, total double, last double, moved double", "append", "NoTimeout"
    )


def replay(spark: SparkSession, folder: str, out: str, checkpoint: str, late: str = "2 hours", files_per_trigger: int | None = None) -> None:
    """All files of folder as a stream into Parquet cells at out; returns when the stream has caught up.

    Append mode: a cell is written once its hour can get no more events, so the last hours wait for a later event.
    """
    cells = hourly_cells(event_stream(spark, folder, files_per_trigger), late)
    query = cells.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()


def watch(spark: SparkSession, folder: str, checkpoint: str, on_cells, files_per_trigger: int = 1):
    """Starts a stream whose closed cells reach on_cells(batch DataFrame, batch number), once each in order.

    on_cells may be run again for a batch after a failure: it should write under the batch's number.
    """
    cells = hourly_cells(event_stream(spark, folder, files_per_trigger))
    return cells.writeStream.foreachBatch(on_cells).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def alarm_sink(store: str, alarms: str, detect, horizon: int):
    """An on_cells that adds each batch to a store of cells, runs detect on the last horizon hours and keeps new alarms.

    detect(panel of cells) gives (z, stat) rows. A batch writes into folders of its own number, so a repeated batch
    replaces what it wrote before. An alarm at an hour that has one is not raised again.
    """

    def on_cells(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.write.mode("overwrite").parquet(f"{store}/batch={number}")
        every = spark.read.parquet(store)
        last = every.agg(F.max("hour")).first()[0]
        if last is None:
            return
        recent = every.where(F.col("hour") > F.lit(last) - F.expr(f"interval {horizon} hours"))
        found = detect(recent).withColumn("batch_no", F.lit(number).cast("long"))
        try:
            known = spark.read.parquet(alarms).where(F.col("batch_no") != number).select("z").distinct()
            found = found.join(known, "z", "left_anti")
        except Exception as missing:  # no alarm so far
            if "PATH_NOT_FOUND" not in str(missing):
                raise
        found.write.mode("overwrite").parquet(f"{alarms}/of={number}")

    return on_cells
