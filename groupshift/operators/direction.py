"""The leading left singular vector of a matrix in column blocks (t, ids, vec), as (series_id, v)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.sources.work import small_batches, work_table

from .relax import columns_of

#: Up to so many active series the Gram matrix of the series goes to the driver, or else up to so many times that of the times: 32 MB of doubles.
GRAM_TIMES = 2048
#: With more of both, up to so many active series their Gram matrix does: 128 MB, and several times that while it comes and is solved.
GRAM_SERIES = 4096
#: Least cells of the slices of series whose Gram matrices are added up; a slice is never smaller than the matrix.
SLICE_CELLS = 500_000


def _oriented(ids, v, spark) -> DataFrame:
    v = kernels.oriented(v)
    return spark.createDataFrame([(int(i), float(x)) for i, x in zip(ids, v, strict=True)], "series_id long, v double")


def active_series(columns: DataFrame) -> list[int]:
    return sorted(r[0] for r in columns.select(F.explode("ids")).distinct().toLocalIterator())


def stored(columns: DataFrame) -> DataFrame:
    """The columns as a work table, if they are none: they are read more than once."""
    return columns if "work_path" in columns.__dict__ else work_table(columns, "columns")


def side(columns: DataFrame) -> str:
    """The side whose Gram matrix is small enough for the driver: series, else times, else neither and the answer is sketch.

    Series that only GRAM_SERIES allows are last: where there are few times, their smaller matrix is taken.
    """
    p = columns.select(F.explode("ids")).distinct().count()
    if p <= min(GRAM_TIMES, GRAM_SERIES):
        return "series"
    if columns.count() <= GRAM_TIMES:
        return "times"
    return "series" if p <= GRAM_SERIES else "sketch"


def cells_of(columns: DataFrame) -> DataFrame:
    return columns.select("t", F.inline(F.arrays_zip("ids", "vec"))).select(F.col("ids").alias("series_id"), "t", F.col("vec").alias("m"))


def rows_of(cells: DataFrame) -> DataFrame:
    """(series_id, ids, vec) of cells (series_id, t, m): each series' times and values, the column blocks of the transposed matrix, as a work table."""
    pairs = F.sort_array(F.collect_list(F.struct("t", "m")))
    rows = cells.groupBy("series_id").agg(pairs.alias("pairs"))
    return work_table(rows.select("series_id", F.col("pairs.t").alias("ids"), F.col("pairs.m").alias("vec")), "rows")


def gram_of_rows(rows: DataFrame):
    """(times, M'M) of the rows (series_id, ids, vec): the matrices of slices of series are added up."""
    import numpy as np

    times = active_series(rows)
    if not times:
        return [], np.zeros((0, 0))
    slices = -(-rows.agg(F.sum(F.size("ids"))).first()[0] // max(SLICE_CELLS, len(times) ** 2))
    return times, _squared(rows.select("ids", "vec").coalesce(slices), rows.sparkSession.sparkContext.broadcast(times))


def gram_of_times(columns: DataFrame):
    """(times, M'M) of columns (t, ids, vec), t unique."""
    return gram_of_rows(rows_of(cells_of(columns)))


def _by_rows(rows: DataFrame) -> DataFrame:
    """M u over the leading singular value, u the leading vector of M'M; the direction itself never is on the driver."""
    import numpy as np

    spark = rows.sparkSession
    times, gram = gram_of_rows(rows)
    if not times:
        return spark.createDataFrame([], "series_id long, v double")
    values, vectors = np.linalg.eigh(gram)
    size = math.sqrt(max(values[-1], 0.0))
    right = spark.sparkContext.broadcast((times, vectors[:, -1] / size if size else np.zeros(len(times))))

    def project(batches):
        import numpy as np
        import pandas as pd

        ids, u = np.array(right.value[0]), right.value[1]
        for batch in batches:
            if len(batch):
                yield pd.DataFrame({"series_id": batch["series_id"], "v": u @ _local(batch, ids)})

    v = work_table(rows.mapInPandas(project, "series_id long, v double"), "direction")
    top = v.agg(F.max(F.abs("v"))).first()[0]
    first = v.where(F.abs("v") > top * (1 - 1e-12)).agg(F.min_by("v", "series_id")).first()[0] or 0.0
    return v.select("series_id", (-F.col("v") if first < 0 else F.col("v")).alias("v"))


def leading_of_cells(cells: DataFrame, n: int, method: str = "auto") -> DataFrame:
    """leading_left of cells (series_id, t, m) of n times at most. Up to GRAM_TIMES of these the rows of the series give the Gram matrix of the
    times, and no column of all series is made; with more times whole columns are gathered and go the way of leading_left."""
    if n <= GRAM_TIMES and method in ("auto", "gram"):
        return _by_rows(rows_of(cells))
    return leading_left(columns_of(cells, "m"), method)


def leading_left(columns: DataFrame, method: str = "auto", steps: int = 100, tol: float = 1e-10, sketch: int = 16) -> DataFrame:
    """method: gram (exact, by the Gram matrix of the series or, if these are many, of the times), power (a pass a step),
    sketch (16 columns at once, a pass a step until the residual is below tol, 1e-9 at least, of the leading value; an
    error after so many steps). auto and gram go by the numbers of series and times, and take the sketch if both are
    many: all ways lead to the same.

    The largest entry in size is positive; of equal ones that of the smallest series. No columns give no rows.
    """
    import numpy as np

    spark = columns.sparkSession
    columns = stored(columns)
    if method in ("auto", "gram"):
        method = side(columns)
        if method == "times":
            return _by_rows(rows_of(cells_of(columns)))
    columns = columns.select("ids", "vec")
    ids = active_series(columns)
    if not ids:
        return spark.createDataFrame([], "series_id long, v double")
    shared = spark.sparkContext.broadcast(ids)
    if method == "series":
        return _oriented(ids, kernels.leading_of_gram(_gram(columns, shared)), spark)
    draw = np.random.default_rng(11)
    if method == "sketch":
        # Columns of the range from random combinations, multiplied again until the leading vector satisfies its equation.
        q = np.linalg.qr(_times(columns, shared, draw.normal(size=(len(ids), min(sketch, len(ids))))))[0]
        for _ in range(steps):
            product = _times(columns, shared, q)
            small = q.T @ product
            values, vectors = np.linalg.eigh((small + small.T) / 2)
            v, value = q @ vectors[:, -1], values[-1]
            residual = np.linalg.norm(product @ vectors[:, -1] - value * v)
            if residual <= max(tol, 1e-9) * max(value, 1e-300):
                return _oriented(ids, v, spark)
            q = np.linalg.qr(product)[0]
        raise RuntimeError(f"after {steps} passes the leading direction is off by {residual / value:.1e} of its value")
    v = np.full((len(ids), 1), 1 / math.sqrt(len(ids)))
    for _ in range(steps):
        new = _times(columns, shared, v)
        size = np.linalg.norm(new)
        if not size:
            break
        new /= size
        moved = np.linalg.norm(new - v)
        v = new
        if moved < tol:
            break
    return _oriented(ids, v[:, 0], spark)


def _local(batch, ids):
    """The batch's columns as a dense matrix over all active series (ascending ids); batches are small beside it."""
    import numpy as np

    m = np.zeros((len(ids), len(batch)))
    sizes = batch["ids"].str.len().to_numpy()
    own, values = np.concatenate(batch["ids"].to_list()), np.concatenate(batch["vec"].to_list())
    m[np.searchsorted(ids, own), np.repeat(np.arange(len(batch)), sizes)] = values
    return m


#: Bytes of a matrix that travel as one row when partitions' matrices are added up.
CHUNK_BYTES = 1 << 20


def _summed(columns: DataFrame, make, shape: tuple[int, int]):
    """The sum over partitions of the matrices make(batches) gives, one for each partition; chunks of rows are added apart."""
    height = max(1, CHUNK_BYTES // (8 * shape[1]))

    def cut(batches):
        import pandas as pd

        total = make(batches)
        if total is not None:
            parts = [total[at : at + height].tobytes() for at in range(0, shape[0], height)]
            yield pd.DataFrame({"i": range(len(parts)), "x": parts})

    return _added(columns.mapInPandas(cut, "i int, x binary"), shape[1])


def _added(rows: DataFrame, width: int):
    """The sum of matrices that came as chunks of rows (i, x), chunk by chunk."""
    import numpy as np

    def add(pdf):
        import pandas as pd

        total = sum(np.frombuffer(x) for x in pdf["x"])
        return pd.DataFrame({"i": [pdf["i"].iloc[0]], "x": [total.tobytes()]})

    with small_batches(rows.sparkSession):
        found = {r["i"]: np.frombuffer(r["x"]).reshape(-1, width) for r in rows.groupBy("i").applyInPandas(add, "i int, x binary").collect()}
    return np.vstack([found[i] for i in range(len(found))])


def _squared(columns: DataFrame, shared):
    """The sum of the columns' outer products."""
    import numpy as np

    p = len(shared.value)

    def make(batches):
        ids, total = np.array(shared.value), None
        for batch in batches:
            for at in range(0, len(batch), 2048):
                m = _local(batch[at : at + 2048], ids)
                total = m @ m.T + (0 if total is None else total)
        return total

    return _summed(columns, make, (p, p))


def _gram(columns: DataFrame, shared):
    """The Gram matrix of the series."""
    return _squared(columns, shared)


def _times(columns: DataFrame, shared, v):
    """M M' v for a thin matrix v that goes to every executor: one pass, no exchange of columns."""
    import numpy as np

    sent = columns.sparkSession.sparkContext.broadcast(v)

    def make(batches):
        ids, total = np.array(shared.value), None
        for batch in batches:
            for at in range(0, len(batch), 256):
                m = _local(batch[at : at + 256], ids)
                total = m @ (m.T @ sent.value) + (0 if total is None else total)
        return total

    return _summed(columns, make, v.shape)
