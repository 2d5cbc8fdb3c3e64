"""What a query costs: seconds, stages, tasks, bytes read, shuffled and spilled, from Spark's own status store."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

FIELDS = {"tasks": "numCompleteTasks", "read_bytes": "inputBytes", "shuffle_bytes": "shuffleWriteBytes", "spill_bytes": "diskBytesSpilled", "task_ms": "executorRunTime"}


def _stages(spark: SparkSession) -> dict[int, dict[str, int]]:
    store = spark.sparkContext._jsc.sc().statusStore()
    found, seq = {}, store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
    for i in range(seq.size()):
        stage = seq.apply(i)
        found[stage.stageId()] = {k: int(getattr(stage, m)()) for k, m in FIELDS.items()}
    return found


def cost_report(spark: SparkSession, run: Callable[[], DataFrame], name: str = "query") -> DataFrame:
    """One row (name, seconds, rows, stages, tasks, read_bytes, shuffle_bytes, spill_bytes, task_ms) for building and running a query."""
    before, began = set(_stages(spark)), time.time()
    rows = run().count()
    seconds = time.time() - began
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    new = [v for k, v in _stages(spark).items() if k not in before]
    sums = [sum(v[k] for v in new) for k in FIELDS]
    return spark.createDataFrame([(name, seconds, rows, len(new), *sums)], "name string, seconds double, rows long, stages int, " + ", ".join(f"{k} long" for k in FIELDS))
