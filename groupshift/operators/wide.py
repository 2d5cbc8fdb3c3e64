"""Detectors over many orders of the times of one panel, dealt to slices of series: nothing of the panel's size is on the driver or in one task.

A variant is (order of the times, place, chosen groups, size): times are put in that order, and a step is added after
the place in all members of the chosen groups, counted in order of group_id; without a place nothing is added.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.sources.work import work_table

#: Detectors that have this form; gsp for disjoint groups.
METHODS = ("gsp", "sparse_projection", "l2", "linf", "double_cusum")
#: Cells of a slice, and cells that a task makes of it over its variants before they leave it.
SLICE_CELLS, TASK_CELLS = 1_000_000, 4_000_000
_PART = "i int, method string, k int, x binary"


def series_rows(panel: DataFrame, groups: DataFrame) -> DataFrame:
    """(series_id, group_id, p_g, x): a row a series, its values by time; series in no group have null group and size."""
    values = F.transform(F.sort_array(F.collect_list(F.struct("t", "x"))), lambda r: r["x"])
    rows = panel.groupBy("series_id").agg(values.alias("x"))
    inside = groups.join(rows.select("series_id"), "series_id", "left_semi")
    sized = inside.join(inside.groupBy("group_id").agg(F.count(F.lit(1)).alias("p_g")), "group_id")
    return work_table(rows.join(sized, "series_id", "left").select("series_id", "group_id", "p_g", "x"), "series_rows")


def _triangle(y):
    import numpy as np

    return np.linalg.qr(y, mode="r")


def _factors(rows: DataFrame, n: int) -> DataFrame:
    """(group_id, p_g, y): rows [x, 1] of each group, or for a group with more members as many rows as columns with the same inner products of columns.

    The grouped detector depends on a group's rows through these products only.
    """
    made = rows.where("group_id is not null").select("group_id", "p_g", "series_id", F.concat("x", F.array(F.lit(1.0))).alias("y"))
    schema = "group_id long, p_g long, y array<double>"

    def reduce(pdf):
        import numpy as np
        import pandas as pd

        out = _triangle(np.stack(pdf["y"].to_list()))
        return pd.DataFrame({"group_id": pdf["group_id"].iloc[0], "p_g": pdf["p_g"].iloc[0], "y": list(out)})

    long = made.where(F.col("p_g") > n + 1).withColumn("part", F.pmod(F.xxhash64("series_id"), F.ceil(F.col("p_g") / (16 * (n + 1)))))
    parts = long.groupBy("group_id", "part").applyInPandas(reduce, schema)
    short = made.where(F.col("p_g") <= n + 1).select("group_id", "p_g", "y")
    return work_table(short.unionByName(parts.groupBy("group_id").applyInPandas(reduce, schema)), "group_factors")


def _dealt(rows: DataFrame, key: str, cells: int, variants: int) -> tuple[DataFrame, int, int]:
    """The rows by (slice, chunk), a chunk being some of the variants; the number of slices and the variants of a chunk."""
    slices = -(-cells // SLICE_CELLS) or 1
    each = max(1, min(TASK_CELLS * slices // max(cells, 1), -(-variants * slices // (4 * rows.sparkSession.sparkContext.defaultParallelism)) or 1))
    chunks = rows.sparkSession.range(-(-variants // each)).select(F.col("id").cast("int").alias("chunk"))
    return rows.withColumn("slice", F.pmod(F.xxhash64(key), F.lit(slices))).crossJoin(F.broadcast(chunks)), slices, each


def _curve(both):
    """|v'C| at each time, from M'M and M'C, v the leading left vector of M."""
    import numpy as np

    inner, cross = np.split(both, 2)
    values, vectors = np.linalg.eigh(inner)
    return np.abs(vectors[:, -1] @ cross) / math.sqrt(values[-1]) if values[-1] > 0 else np.zeros(len(cross))


def _pieces(i: int, method: str, x):
    """Rows of _PART of a matrix of two stacked squares, in chunks that are added up apart."""
    height = max(1, (1 << 20) // (8 * x.shape[1]))
    return [(i, method, k, x[at : at + height].tobytes()) for k, at in enumerate(range(0, len(x), height))]


def detect_orders(panel: DataFrame, groups: DataFrame, variants: list, lam: float, methods=("gsp",)) -> DataFrame:
    """(i, method, z, stat) of each variant, by its place in the list, and method. Groups are disjoint where gsp is asked for."""
    if set(methods) - set(METHODS):
        raise ValueError(f"panels dealt to slices have no {sorted(set(methods) - set(METHODS))}")
    spark = panel.sparkSession
    rows = series_rows(panel, groups)
    counted = rows.agg(F.count(F.lit(1)).alias("p"), F.max(F.size("x")).alias("n"), F.min(F.size("x")).alias("least")).first()
    p, n = counted["p"], counted["n"] or 0
    if n != counted["least"]:
        raise ValueError("a panel needs every series at every time")
    sizes = {r["group_id"]: r["p_g"] for r in rows.where("group_id is not null").select("group_id", "p_g").distinct().toLocalIterator()}
    names = sorted(sizes)
    steps = []
    for order, z, chosen, size in variants:
        members = {names[g] for g in chosen}
        steps.append((order, z, members, size / math.sqrt(max(1, sum(sizes[g] for g in members)))))
    sent = spark.sparkContext.broadcast(steps)

    def moved(x, own, step):
        order, z, members, height = step
        out = x[:, order]
        if z is not None and members:
            out[[g in members for g in own], z:] += height
        return out

    def by_rows(pdf):
        import numpy as np
        import pandas as pd

        x, own, level, out = np.stack(pdf["x"].to_list()), pdf["group_id"].to_list(), kernels.sparse_level(p, n), []
        first = int(pdf["chunk"].iloc[0]) * each
        for i, step in enumerate(sent.value[first : first + each], first):
            c = kernels.cusum(moved(x, own, step))
            a = np.abs(c)
            if "l2" in methods:
                out.append((i, "l2", 0, (c * c).sum(0).tobytes()))
            if "linf" in methods:
                out.append((i, "linf", 0, a.max(0).tobytes()))
            if "sparse_projection" in methods:
                m = np.sign(c) * np.maximum(a - level, 0)
                out += _pieces(i, "sparse_projection", np.vstack([m.T @ m, m.T @ c]))
            if "double_cusum" in methods:
                out += [(i, "double_cusum", t, a[:, t].tobytes()) for t in range(n - 1)]
        return pd.DataFrame(out, columns=["i", "method", "k", "x"])

    def by_groups(pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.sort_values("group_id", kind="stable")
        y, own = np.stack(pdf["y"].to_list()), pdf["group_id"].to_numpy()
        starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
        counts, bound = np.diff(np.r_[starts, len(own)]), lam * np.sqrt(pdf["p_g"].to_numpy()[starts])[:, None]
        out, first = [], int(pdf["chunk"].iloc[0]) * group_each
        for i, (order, z, members, height) in enumerate(sent.value[first : first + group_each], first):
            x = y[:, :n][:, order]
            if z is not None:
                here = np.isin(own, list(members))
                x[here, z:] += height * y[here, n:]  # the last column stands for a one in every member
            c = kernels.cusum(x)
            norm = np.sqrt(np.add.reduceat(c * c, starts, axis=0))
            m = c * np.repeat(np.maximum(0, 1 - bound / np.where(norm > 0, norm, 1)) * (norm > 0), counts, axis=0)
            both = np.vstack([m.T @ m, m.T @ c])
            out += _pieces(i, "gsp", both) if group_slices > 1 else [(i, "gsp", -1, _curve(both).tobytes())]
        return pd.DataFrame(out, columns=["i", "method", "k", "x"])

    def add(pdf):
        import numpy as np
        import pandas as pd

        i, method, k = (pdf[c].iloc[0] for c in ("i", "method", "k"))
        found = [np.frombuffer(x) for x in pdf["x"]]
        if method == "double_cusum":
            total = kernels.double_cusum(np.concatenate(found)[:, None])
        else:
            total = np.max(found, axis=0) if method == "linf" else sum(found)
        return pd.DataFrame({"i": [i], "method": [method], "k": [k], "x": [total.tobytes()]})

    def finish(pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.sort_values("k")
        i, method = pdf["i"].iloc[0], pdf["method"].iloc[0]
        curve = np.concatenate([np.frombuffer(x) for x in pdf["x"]])
        if method == "l2":
            curve = np.sqrt(curve)
        elif method in ("gsp", "sparse_projection") and pdf["k"].iloc[0] >= 0:
            curve = _curve(curve.reshape(-1, n - 1))
        z, stat = kernels.peak(curve)
        return pd.DataFrame({"i": [i], "method": [method], "z": pd.array([z], "Int64"), "stat": [stat]})

    out = None
    if set(methods) - {"gsp"}:
        dealt, _, each = _dealt(rows, "series_id", p * n, len(variants))
        out = dealt.groupBy("slice", "chunk").applyInPandas(by_rows, _PART)
    if "gsp" in methods:
        factors = _factors(rows, n)
        dealt, group_slices, group_each = _dealt(factors, "group_id", factors.count() * (n + 1), len(variants))
        part = dealt.groupBy("slice", "chunk").applyInPandas(by_groups, _PART)
        out = part if out is None else out.unionByName(part)
    summed = out.groupBy("i", "method", "k").applyInPandas(add, _PART)
    return summed.groupBy("i", "method").applyInPandas(finish, "i int, method string, z long, stat double")
