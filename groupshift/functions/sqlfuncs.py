"""Functions for SQL: native expressions as temporary SQL functions, a pandas UDF, a grouped UDF and a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from groupshift import kernels

#: SQL bodies; they are inlined, so no Python runs.
SCALARS = {
    "gs_cusum_point(pref DOUBLE, tot DOUBLE, t DOUBLE, n DOUBLE) RETURNS DOUBLE": "CASE WHEN t > 0 AND t < n THEN (t * tot - n * pref) / sqrt(n * t * (n - t)) END",
    "gs_lambda(n DOUBLE, g DOUBLE, least_size DOUBLE, sigma DOUBLE) RETURNS DOUBLE": "sigma * (1 + sqrt(4 * ln(g * n) / least_size))",
    "gs_sin_theta(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": (
        "sqrt(greatest(1 - pow(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), 2)"
        " / nullif(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x), 0D), 0D))"
    ),
    "gs_block_norm(v ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(v, 0D, (s, x) -> s + x * x))",
}


def register(spark: SparkSession) -> None:
    for head, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")

    def shrink(vec: pd.Series, level: pd.Series) -> pd.Series:
        import numpy as np

        def one(v, least):
            v = np.asarray(v, float)
            size = np.linalg.norm(v)
            return (v * max(0.0, 1 - least / size) if size else v).tolist()

        return pd.Series([one(v, x) for v, x in zip(vec, level, strict=True)])

    def argmax_abs(t: pd.Series, value: pd.Series) -> int:
        a = value.abs()
        return int(t[a == a.max()].min())

    spark.udf.register("gs_shrink", F.pandas_udf(shrink, "array<double>"))
    spark.udf.register("gs_argmax_abs", F.pandas_udf(argmax_abs, "long"))
    spark.udtf.register("gs_detect", detect_udtf())


def detect_udtf():
    """SELECT * FROM gs_detect(TABLE(panel) PARTITION BY rep ORDER BY (t, series_id)): (rep, z, stat) for each panel of rows (rep, series_id, t, x).

    Every series is its own group; the level is that of the detector without groups.
    """

    class Detect:
        def __init__(self):
            self.rep, self.cells = None, {}

        def eval(self, row):
            self.rep = row["rep"]
            self.cells.setdefault(row["series_id"], []).append(row["x"])

        def terminate(self):
            import numpy as np

            if self.cells:
                z, stat, _ = kernels.sparse_projection(np.array([self.cells[k] for k in sorted(self.cells)]))
                yield self.rep, z, stat

    return F.udtf(Detect, returnType="rep int, z long, stat double")
