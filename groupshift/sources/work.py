"""Work tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one where it is unset and all run on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is unset: name a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="groupshift-"))
        base = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    elif not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(base)
    return base


def _forget(spark: SparkSession, path: str) -> None:
    """Deletes a work table when the driver ends; the session may be gone by then."""
    sc = spark.sparkContext
    if sc._jsc is None:
        return
    with contextlib.suppress(Py4JError):  # the JVM is gone
        where = sc._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


#: Rows of an Arrow batch while a work table is written: with texts in them, Spark's own 10,000 take tens of megabytes a task.
BATCH_ROWS = 1000


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Arrow batches of BATCH_ROWS rows for what runs inside; the session's setting is put back after."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = int(spark.conf.get(key))
    spark.conf.set(key, str(min(before, BATCH_ROWS) if before > 0 else BATCH_ROWS))
    try:
        yield
    finally:
        spark.conf.set(key, str(before))


def work_table(df: DataFrame, name: str, rows: int | None = None, each: int = 250_000) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage ends here, and lost executors cost no recomputation.

    Partitions are gathered into fewer files, each still read one after the other by its task: about each rows in a
    file where the caller knows a bound on the rows, else half the shuffle partitions, and never fewer than keep all
    cores busy. Small tables so stay a few files.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/work-{uuid.uuid4().hex}/{name}"
    if rows is None:
        files = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")) // 2)
    else:
        files = max(1, -(-rows // each))
    with small_batches(spark):
        df.coalesce(files).write.parquet(path)
    atexit.register(_forget, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out.work_path = path
    return out


def drop_table(table: DataFrame) -> None:
    """Deletes a work table that nothing reads any more; any other DataFrame is left alone."""
    path = getattr(table, "__dict__", {}).get("work_path")
    if path:
        _forget(table.sparkSession, path)
