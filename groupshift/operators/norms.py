"""Norms of vectors (series_id, v) and matrices (series_id, t, value)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import direction
from .groups import sizes


def vec_norms(vec: DataFrame) -> DataFrame:
    """One row: number of non-zero entries, l1, l2 and largest size."""
    a = F.abs("v")
    return vec.agg(
        F.sum(F.when(F.col("v") != 0, 1).otherwise(0)).cast("long").alias("l0"), F.sum(a).alias("l1"), F.sqrt(F.sum(a * a)).alias("l2"), F.max(a).alias("linf")
    )


def phi(vec: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, norm): each group's l2 norm."""
    return groups.join(vec, "series_id").groupBy("group_id").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))


def block_norms(m: DataFrame, groups: DataFrame, value: str = "cusum") -> DataFrame:
    """(group_id, t, norm, p_g)."""
    per = groups.join(sizes(groups), "group_id")
    joined = m.join(per, "series_id")
    return joined.groupBy("group_id", "t").agg(F.sqrt(F.sum(F.col(value) * F.col(value))).alias("norm"), F.first("p_g").alias("p_g"))


def group_norm(m: DataFrame, groups: DataFrame, value: str = "cusum") -> DataFrame:
    return block_norms(m, groups, value).agg(F.sum(F.sqrt("p_g") * F.col("norm")).alias("group_norm"))


def dual_norm(m: DataFrame, groups: DataFrame, value: str = "cusum") -> DataFrame:
    """The dual of the group norm for disjoint groups; for overlapping ones an upper bound of it."""
    return block_norms(m, groups, value).agg(F.max(F.col("norm") / F.sqrt("p_g")).alias("dual_norm"))


def frobenius(m: DataFrame, value: str = "cusum") -> DataFrame:
    return m.agg(F.sqrt(F.sum(F.col(value) * F.col(value))).alias("frobenius"))


def inner(a: DataFrame, b: DataFrame, value: str = "cusum") -> DataFrame:
    right = b.select("series_id", "t", F.col(value).alias("other"))
    return a.join(right, ["series_id", "t"]).agg(F.sum(F.col(value) * F.col("other")).alias("inner"))


def restrict(m: DataFrame, series: DataFrame | None = None, first: int | None = None, last: int | None = None) -> DataFrame:
    """The submatrix of some series and times."""
    if first is not None:
        m = m.where(F.col("t") >= first)
    if last is not None:
        m = m.where(F.col("t") <= last)
    return m if series is None else m.join(series.select("series_id"), "series_id", "left_semi")


def spectral(columns: DataFrame) -> DataFrame:
    """One row (operator, nuclear) of a matrix in column blocks, from the Gram matrix of its active series or, if these are many, of its times.

    All singular values are wanted, so one side has to be small; if neither is, an error is raised.
    """
    import numpy as np

    columns = direction.stored(columns)
    by = direction.side(columns)
    if by == "sketch":
        raise ValueError(f"more than {direction.GRAM_SERIES} active series and more than {direction.GRAM_TIMES} times: all singular values would need a matrix of either side")
    if by == "times":
        gram = direction.gram_of_times(columns)[1]
    else:
        ids = direction.active_series(columns)
        gram = direction._gram(columns.select("ids", "vec"), columns.sparkSession.sparkContext.broadcast(ids)) if ids else np.zeros((1, 1))
    # There are no more singular values than the smaller side is long: what a matrix of the other side has beyond them is rounding.
    least = min(columns.count(), columns.select(F.explode("ids")).distinct().count())
    values = np.sqrt(np.maximum(np.linalg.eigvalsh(gram)[::-1][: max(1, least)], 0))
    return columns.sparkSession.createDataFrame([(float(values.max()), float(values.sum()))], "operator double, nuclear double")
