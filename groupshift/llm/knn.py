"""Exact top-k search as a Voronoi kNN join.

Vectors are dealt to the pivot nearest to them. From each cell's summary (size, radius) follow bounds on every score
between a cell of queries and a cell of data; a query cell's k-th best lower bound tells which cells it can do without. Data
rows are copied to the groups of queries that need their cell, and each block of queries and data is solved by a matrix product.

Scores are exact: products of vectors short enough that a double holds every sum go through doubles, all others through
Python's integers. The few vectors that are too long for doubles form a cell of their own, which everybody needs.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import frugal, work_table

#: Two vectors up to this squared length have a product, and all sums on the way to it, that a double holds exactly.
EXACT = 2**52
#: More pivots than this do not fit the driver's plan: cells squared bounds, pivots in every executor.
MOST_CELLS = 8192
LONG_MIN, LONG_MAX = -(2**63), 2**63 - 1
#: The cell and the query group of vectors that are too long for doubles.
WILD = -1


def sound_vectors(vectors: DataFrame, embedding: str = "embedding") -> DataFrame:
    """(vec_id, x): vectors as doubles; those that are null or hold a null or non-finite component are left out."""
    doubles = F.transform(F.col(embedding), lambda x: x.cast("double"))
    finite = F.forall(doubles, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    rows = vectors.select("vec_id", F.when(F.coalesce(finite, F.lit(False)), doubles).alias("x"))
    return rows.where("x is not null and vec_id is not null")


def _matrix(arrays, width: int):
    import numpy as np

    out = np.zeros((len(arrays), width))
    for i, row in enumerate(arrays):
        out[i, : len(row)] = row
    return out


def quantised(m, scale: int):
    """floor(scale * x) in doubles; infinite where that is beyond them."""
    import numpy as np

    with np.errstate(over="ignore"):
        return np.floor(m * scale)


def _exact(row, scale: int) -> list[int]:
    """floor(scale * x) of each component as Python integers, whatever their size."""
    return [math.floor(Fraction(float(x)) * scale) for x in row]


def _order(score: int) -> str:
    """A string that sorts as the scores do, for those that a long does not hold; empty for the others."""
    if LONG_MIN <= score <= LONG_MAX:
        return ""
    digits = str(abs(score))
    word = f"{len(digits):05d}{digits}"
    return word if score > 0 else "".join(chr(ord("9") - int(c) + ord("0")) for c in word) + "~"


def _top(scores, ids, k: int):
    """Row by row the places of the k highest scores, ties to the smaller id; -inf is no candidate."""
    import numpy as np

    if scores.shape[1] > 4 * k:
        least = np.partition(scores, -k, axis=1)[:, -k]
    else:
        least = np.full(len(scores), -np.inf)
    for i, row in enumerate(scores):
        at = np.flatnonzero(row >= least[i])
        at = at[np.lexsort((ids[at], -row[at]))][:k]
        yield i, at[row[at] > -np.inf]


@dataclass(frozen=True)
class Search:
    result: DataFrame  # query_id, rank, vec_id, score
    cells: int
    pairs_needed: int  # pairs of a query and a vector whose cells cannot be left out
    pairs_solved: int  # pairs that are multiplied: a group of query cells shares the data that one of them needs
    pairs: int  # all pairs


def top_k(vectors: DataFrame, **options) -> DataFrame:
    """query_id, rank, vec_id, score of search."""
    return search(vectors, **options).result


def search(
    vectors: DataFrame,
    queries_every: int = 50,
    k: int = 5,
    scale: int = 256,
    cells: int | None = None,
    group_queries: int = 2048,
    block_rows: int = 16384,
) -> Search:
    """The k highest integer inner products for each query among all other rows, and how many pairs that took.

    vectors has vec_id and embedding; rows whose vec_id is divisible by queries_every are queries. Vectors that are null
    or hold a null or non-finite component take no part; all others do, however large. Missing components of shorter
    vectors count as 0. Ties go to the smaller vec_id. Of rows that repeat a vec_id each is a row of its own: another's
    partner, not its own. A null vec_id is no query and no answer. Fewer candidates than k give fewer rows. Ranks go by exact
    integers; a score that no long holds is shown as the nearest one. Pivots are vectors picked by hash, the
    square root of the rows by default; they bear on cost, not on results.
    """
    spark = vectors.sparkSession
    base = work_table(sound_vectors(vectors).withColumn("uid", F.monotonically_increasing_id()), "vectors")
    is_query = F.col("vec_id") % queries_every == 0
    summary = base.agg(F.max(F.size("x")).alias("width"), F.count(F.lit(1)).alias("n"), F.sum(is_query.cast("long")).alias("q")).first()
    width, n, n_queries = max(1, summary["width"] or 1), summary["n"], summary["q"] or 0
    none = Search(spark.createDataFrame([], "query_id long, rank int, vec_id long, score long"), 0, 0, 0, 0)
    if not n or not n_queries:
        return none
    cells = max(1, min(MOST_CELLS, math.isqrt(n) if cells is None else cells))
    picked = base.orderBy(F.xxhash64("uid"), "uid").limit(cells).select("x").collect()
    pivots = quantised(_matrix([r["x"] for r in picked], width), scale)
    pivots = pivots[(pivots * pivots).sum(1) <= EXACT]
    shared = spark.sparkContext.broadcast(pivots)

    def assign(batches):
        import numpy as np
        import pyarrow as pa

        p = shared.value
        norms = (p * p).sum(1)
        for batch in batches:
            v = quantised(_matrix(batch.column("x").to_pylist(), width), scale)
            with np.errstate(over="ignore"):
                tame = (v * v).sum(1) <= EXACT
            near, away = np.full(len(v), WILD), np.zeros(len(v))
            if len(p) and tame.any():
                m = v[tame]
                near[tame] = (norms - 2 * m @ p.T).argmin(1)
                away[tame] = np.sqrt(((m - p[near[tame]]) ** 2).sum(1))
            batch = batch.append_column("cell", pa.array(near.astype("int32")))
            yield batch.append_column("away", pa.array(away))

    dealt = work_table(base.mapInArrow(frugal(assign), "vec_id long, x array<double>, uid long, cell int, away double"), "cells")
    about = dealt.groupBy("cell").agg(
        F.count(F.lit(1)).alias("n"), F.max("away").alias("radius"),
        F.sum(is_query.cast("long")).alias("nq"), F.max(F.when(is_query, F.col("away"))).alias("q_radius"),
    ).collect()
    plan = _plan(pivots, about, k, group_queries, block_rows)
    # Rows of a cell or a group are split by a hash of their number, so a frequent vector fills no task.
    needs = spark.createDataFrame(plan.needs, "c int, grp int, q_parts int, bin int, d_parts int")
    hosts = spark.createDataFrame(plan.hosts, "c int, q_grp int, q_parts int")
    bins = spark.createDataFrame(plan.bins, "g int, q_bin int, d_parts int")
    spread = lambda n: F.pmod(F.xxhash64("uid"), n).cast("int")
    data = dealt.join(F.broadcast(needs), F.col("cell") == F.col("c")).withColumn("part", spread(F.col("d_parts")))
    data = data.withColumn("q_part", F.explode(F.sequence(F.lit(0), F.col("q_parts") - 1))).select("grp", "q_part", "bin", "part", "uid", "vec_id", "x")
    # A query goes to the bins of data that its group needs, and to no others.
    asked = dealt.where(is_query).join(F.broadcast(hosts), F.col("cell") == F.col("c")).withColumn("q_of", spread(F.col("q_parts")))
    asked = asked.join(F.broadcast(bins), F.col("q_grp") == F.col("g")).withColumn("q_block", F.explode(F.sequence(F.lit(0), F.col("d_parts") - 1)))
    asked = asked.select("q_grp", "q_of", "q_bin", "q_block", F.col("uid").alias("q_uid"), F.col("vec_id").alias("query_id"), F.col("x").alias("q_x"))
    fields = ("q_uid", "query_id", "uid", "vec_id", "score", "wide")

    def solve(q, d):
        import numpy as np
        import pandas as pd

        out = []

        def add(i, best, scores):
            out.append(pd.DataFrame({"q_uid": own[i], "query_id": q["query_id"].iloc[i], "uid": uids[best], "vec_id": ids[best], "score": scores, "wide": ""}))

        if len(q) and len(d):
            ids, uids, own = d["vec_id"].to_numpy(), d["uid"].to_numpy(), q["q_uid"].to_numpy()
            m, asked_m = quantised(_matrix(d["x"].tolist(), width), scale), quantised(_matrix(q["q_x"].tolist(), width), scale)
            with np.errstate(over="ignore"):
                tame, asked_tame = (m * m).sum(1) <= EXACT, (asked_m * asked_m).sum(1) <= EXACT
            m[~tame] = 0.0
            for at in range(0, len(q), 256):
                rows = np.flatnonzero(asked_tame[at : at + 256]) + at
                scores = asked_m[rows] @ m.T
                scores[own[rows, None] == uids[None, :]] = -np.inf
                scores[:, ~tame] = -np.inf
                for i, best in _top(scores, ids, k):
                    add(rows[i], best, scores[i, best].astype("int64"))
            # Pairs with a vector that is too long for doubles.
            large = {int(j): _exact(d["x"].iloc[j], scale) for j in np.flatnonzero(~tame)}
            for i in range(len(q)) if large else np.flatnonzero(~asked_tame):
                mine = _exact(q["q_x"].iloc[i], scale)
                found = []
                for j in range(len(d)) if not asked_tame[i] else large:
                    if uids[j] != own[i]:
                        other = large[j] if j in large else _exact(d["x"].iloc[j], scale)
                        found.append((-sum(a * b for a, b in zip(mine, other, strict=False)), int(ids[j]), j))
                best = sorted(found)[:k]
                if best:
                    add(i, [j for *_, j in best], [min(LONG_MAX, max(LONG_MIN, -s)) for s, *_ in best])
                    out[-1]["wide"] = [_order(-s) for s, *_ in best]
        if not out:
            return pd.DataFrame({c: pd.Series([], dtype="object" if c == "wide" else "int64") for c in fields})
        return pd.concat(out)

    groups = asked.groupBy("q_grp", "q_of", "q_bin", "q_block").cogroup(data.groupBy("grp", "q_part", "bin", "part"))
    local = groups.applyInPandas(solve, "q_uid long, query_id long, uid long, vec_id long, score long, wide string")
    order = Window.partitionBy("q_uid").orderBy(F.desc("score"), F.desc("wide"), "vec_id", "uid")
    result = local.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
    return Search(result, len(about), plan.pairs_needed, plan.pairs_solved, n * n_queries)


@dataclass(frozen=True)
class _Plan:
    needs: list[tuple]  # cell, group, parts of the group's queries, bin of the cell, parts of the bin: data to be copied
    hosts: list[tuple]  # cell, group of its queries, parts
    bins: list[tuple]  # group, bin that it needs, parts of the bin
    pairs_needed: int
    pairs_solved: int


def _plan(pivots, about, k: int, group_queries: int, block_rows: int) -> _Plan:
    """Which group of queries needs which cells; bounded by the number of cells squared.

    For a query within rho of pivot a and data within r of pivot p, their product is a.p give or take
    |a| r + |p| rho + r rho. Small cells are gathered into bins of about block_rows rows, large ones split into as many parts.
    """
    import numpy as np

    about = sorted(about, key=lambda r: r["cell"])
    wild = [r for r in about if r["cell"] == WILD]
    rest = [r for r in about if r["cell"] != WILD]
    cells, count = np.array([r["cell"] for r in rest], int), np.array([r["n"] for r in rest], float)
    radius = np.array([r["radius"] for r in rest])
    p = pivots[cells] if len(cells) else np.zeros((0, 1))
    p_norm = np.sqrt((p * p).sum(1))
    # Bins of data cells that lie together.
    chain = _chain(p)
    bin_of, parts_of, filled, at = {}, {}, 0, 0
    for j in chain:
        if filled and filled + count[j] > block_rows:
            at, filled = at + 1, 0
        filled += count[j]
        bin_of[int(cells[j])] = at
        parts_of[at] = max(1, math.ceil(filled / block_rows))
    if wild:
        bin_of[WILD], parts_of[at + 1] = at + 1, max(1, math.ceil(wild[0]["n"] / block_rows))
    # Groups of query cells that lie together.
    group_of, size_of, grp = {}, {0: 0}, 0
    for j in chain:
        nq = rest[j]["nq"]
        if nq:
            if size_of[grp] and size_of[grp] + nq > group_queries:
                grp += 1
                size_of[grp] = 0
            size_of[grp] += nq
            group_of[int(cells[j])] = grp
    if wild and wild[0]["nq"]:
        group_of[WILD] = WILD
        size_of[WILD] = wild[0]["nq"]
    q_parts = {g: max(1, math.ceil(n / group_queries)) for g, n in size_of.items()}
    needed: dict[int, set[int]] = {}
    n_wild, pairs_needed = sum(r["n"] for r in wild), 0
    for j, r in enumerate(rest):
        if not r["nq"]:
            continue
        a, rho = p[j], r["q_radius"]
        middle, give = p @ a, np.linalg.norm(a) * radius + p_norm * rho + radius * rho
        give += 1e-9 * (np.abs(middle) + give) + 1e-6
        low = middle - give
        order = np.argsort(-low)
        have = np.cumsum(count[order])
        enough = np.flatnonzero(have >= k + 1)  # the query itself may be one of those counted
        sure = low[order[enough[0]]] if len(enough) else -np.inf
        take = np.flatnonzero(middle + give >= sure)
        needed.setdefault(group_of[int(cells[j])], set()).update(int(cells[x]) for x in take)
        pairs_needed += int(r["nq"]) * (int(count[take].sum()) + n_wild)
    every = [int(c) for c in cells] + [WILD] * bool(wild)
    for g in set(group_of.values()):
        needed.setdefault(g, set()).update(every if g == WILD else [WILD] * bool(wild))
    sizes = {r["cell"]: r["n"] for r in about}
    pairs_needed += size_of.get(WILD, 0) * sum(sizes.values())
    needs = [(c, g, q_parts[g], bin_of[c], parts_of[bin_of[c]]) for g, found in sorted(needed.items()) for c in sorted(found)]
    bins = sorted({(g, b, d) for _, g, _, b, d in needs})
    solved = sum(size_of[g] * sizes[c] for c, g, *_ in needs)
    return _Plan(needs, [(c, g, q_parts[g]) for c, g in group_of.items()], bins, pairs_needed, solved)


def _chain(p) -> list[int]:
    """The rows of p in an order in which each is followed by the nearest that is left."""
    import numpy as np

    if not len(p):
        return []
    norms, left = (p * p).sum(1), np.ones(len(p), bool)
    out = [0]
    left[0] = False
    for _ in range(len(p) - 1):
        away = np.where(left, norms - 2 * p @ p[out[-1]], np.inf)
        out.append(int(away.argmin()))
        left[out[-1]] = False
    return out
