"""The relaxed problem on column blocks: closed form, iterative solver, column-separable solver.

A block row is (group_id or component, t, ids, vec): the values of some series at one time, ids ascending.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.sources.work import drop_table, work_table

from .groups import sizes


#: Most rows of a grouping that go to every executor, about 24 bytes each.
BROADCAST_ROWS = 2_000_000


def sized_groups(groups: DataFrame) -> DataFrame:
    """(group_id, series_id, p_g), broadcast where a count shows that it is small."""
    sized = groups.join(sizes(groups), "group_id")
    return F.broadcast(sized) if groups.count() <= BROADCAST_ROWS else sized


def to_blocks(c: DataFrame, groups: DataFrame, value: str = "cusum") -> DataFrame:
    """(group_id, t, p_g, ids, vec) from long rows: the one exchange that turns rows of series into columns."""
    joined = c.join(sized_groups(groups), "series_id")
    pairs = F.sort_array(F.collect_list(F.struct("series_id", F.col(value).alias("x"))))
    grouped = joined.groupBy("group_id", "t", "p_g").agg(pairs.alias("pairs"))
    return grouped.select("group_id", "t", "p_g", F.col("pairs.series_id").alias("ids"), F.col("pairs.x").alias("vec"))


def shrink_blocks(blocks: DataFrame, lam: float) -> DataFrame:
    """The blocks that survive, shrunk; a block no longer than lam * sqrt(p_g) is dropped."""
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x))
    kept = blocks.withColumn("norm", norm).where(F.col("norm") > lam * F.sqrt("p_g"))
    # Spark puts an outer column's expression into the lambda that names it: a norm in there would be taken anew for every entry.
    factors = F.array_repeat(1 - lam * F.sqrt("p_g") / F.col("norm"), F.size("vec"))
    return kept.select("group_id", "t", "p_g", "norm", "ids", F.zip_with("vec", factors, lambda x, f: x * f).alias("vec"))


def block_shrink(c: DataFrame, groups: DataFrame, lam: float, normalise: bool = False) -> DataFrame:
    """(series_id, t, m) of the closed form for disjoint groups; zero entries are left out."""
    shrunk = shrink_blocks(to_blocks(c, groups), lam)
    long = shrunk.select("t", F.inline(F.arrays_zip("ids", "vec"))).select(F.col("ids").alias("series_id"), "t", F.col("vec").alias("m"))
    if not normalise:
        return long
    size = long.agg(F.sqrt(F.sum(F.col("m") * F.col("m")))).first()[0]
    return long.withColumn("m", F.col("m") / (size or 1.0))


def active_groups(c: DataFrame, groups: DataFrame, lam: float) -> DataFrame:
    """(group_id, blocks, longest): groups with a block that survives; the others bear on nothing after this step."""
    shrunk = shrink_blocks(to_blocks(c, groups), lam)
    return shrunk.groupBy("group_id").agg(F.count(F.lit(1)).alias("blocks"), F.max("norm").alias("longest"))


def columns_of(c: DataFrame, value: str = "cusum") -> DataFrame:
    """(t, ids, vec): whole columns, for solvers that need every overlapping group of a time point."""
    pairs = F.sort_array(F.collect_list(F.struct("series_id", F.col(value).alias("x"))))
    return c.groupBy("t").agg(pairs.alias("pairs")).select("t", F.col("pairs.series_id").alias("ids"), F.col("pairs.x").alias("vec"))


def membership(groups: DataFrame) -> dict[int, list[int]]:
    """group -> members, on the driver: one number for each membership, as the direction has for each series.

    More than BROADCAST_ROWS memberships raise an error: solvers of whole columns need the grouping in every task.
    """
    n = groups.count()
    if n > BROADCAST_ROWS:
        raise ValueError(f"{n} memberships are more than {BROADCAST_ROWS}: use the closed form on disjoint groups")
    out: dict[int, list[int]] = {}
    for row in groups.orderBy("group_id", "series_id").toLocalIterator():
        out.setdefault(row["group_id"], []).append(row["series_id"])
    return out


def _kernel_frame(batch, members):
    """(times, ids, matrix, groups as row numbers) of a batch of whole columns."""
    import numpy as np

    ids = np.array(batch["ids"].iloc[0])
    place = {int(s): i for i, s in enumerate(ids)}
    groups = [np.array([place[s] for s in m if s in place]) for m in members.values()]
    return batch["t"].to_numpy(), ids, np.array(batch["vec"].tolist()).T, [g for g in groups if len(g)]


_LONG = "t long, ids array<long>, vec array<double>"


def _emit(times, ids, m):
    import pandas as pd

    return pd.DataFrame({"t": times, "ids": [ids.tolist()] * len(times), "vec": list(m.T.tolist())})


def columnwise_dual(columns: DataFrame, groups: DataFrame, lam: float, tol: float = 1e-9, sweeps: int = 500) -> DataFrame:
    """The exact solution before normalising, column by column: one pass, no talk between columns, any overlap."""
    members = groups.sparkSession.sparkContext.broadcast(membership(groups))

    def run(batches):
        for batch in batches:
            if len(batch):
                times, ids, c, g = _kernel_frame(batch, members.value)
                yield _emit(times, ids, kernels.columnwise_dual(c, g, lam, tol, sweeps))

    return columns.mapInPandas(run, _LONG)


def conditional_gradient(
    columns: DataFrame, groups: DataFrame, lam: float, eps: float = 1e-4, max_iter: int = 200, save_every: int = 10
) -> DataFrame:
    """The iterative solver over whole columns.

    A step needs two sums over all columns, |g|^2 and <m, g>. Every job loads the state that was last saved,
    repeats the steps since from their known sums, and adds up the next two; every save_every steps the state is
    written to the shared folder, so lineage stays short and a lost executor repeats few steps.
    """
    members = groups.sparkSession.sparkContext.broadcast(membership(groups))
    size = columns.select(F.sqrt(F.sum(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x)))).first()[0] or 0.0
    if not size:
        return columns
    state = columns.withColumn("m", F.transform("vec", lambda x: x / F.lit(size)))
    known: list[tuple[int, float, float]] = []

    def replay(batch, since):
        import numpy as np

        times, ids, c, g = _kernel_frame(batch, members.value)
        m = np.array(batch["m"].tolist()).T
        for k, norm2, inner in since:
            m, _ = kernels.blend(m, c - kernels.penalty_slope(m, g, lam), k, norm2, inner)
        return times, ids, c, g, m

    def sums(batches, since):
        import pandas as pd

        for batch in batches:
            if len(batch):
                _, _, c, g, m = replay(batch, since)
                slope = c - kernels.penalty_slope(m, g, lam)
                yield pd.DataFrame({"norm2": [float((slope * slope).sum())], "dot": [float((m * slope).sum())]})

    def states(batches, since):
        import pandas as pd

        for batch in batches:
            if len(batch):
                times, ids, c, _, m = replay(batch, since)
                yield pd.DataFrame({"t": times, "ids": [ids.tolist()] * len(times), "vec": batch["vec"], "m": list(m.T.tolist())})

    for k in range(1, max_iter + 1):
        since = list(known)
        r = state.mapInPandas(lambda b, s=since: sums(b, s), "norm2 double, dot double").agg(F.sum("norm2").alias("a"), F.sum("dot").alias("b")).first()
        if not r["a"]:
            break
        known.append((k, r["a"], r["b"]))
        a, b, length = k / (k + 2), 2 / (k + 2), math.sqrt(r["a"])
        norm = math.sqrt(a * a + 2 * a * b * r["b"] / length + b * b)
        done = math.sqrt(max(0.0, 2 - 2 * (a + b * r["b"] / length) / norm)) <= eps
        if len(known) >= save_every or done or k == max_iter:
            before, state = state, work_table(state.mapInPandas(lambda x, s=list(known): states(x, s), f"{_LONG}, m array<double>"), "solver_state")
            drop_table(before)
            known = []
        if done:
            break
    return state.select("t", "ids", F.col("m").alias("vec"))


def to_long(columns: DataFrame, name: str = "m") -> DataFrame:
    return columns.select("t", F.inline(F.arrays_zip("ids", "vec"))).select(F.col("ids").alias("series_id"), "t", F.col("vec").alias(name))
