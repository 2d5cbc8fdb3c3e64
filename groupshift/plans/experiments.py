"""The experiment workloads. Each replicate is one row of work; data sets are drawn or derived where they are used.

Defaults are the published settings. reps, sizes and grids are parameters, so that a smaller run says how small it is.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from groupshift import kernels
from groupshift.functions import tuning
from groupshift.operators import groups as gr
from groupshift.operators import multi, relax, scale, single, wide
from groupshift.sources import panels

RUN = "config_id string, rep int, method string, z_true long, z_hat long, loss double, stat double"
DYADIC = (1.0, 2.0, 4.0, 8.0, 16.0)
DIVISORS_OF_60 = (1, 2, 3, 4, 5, 6, 10, 12, 15, 20, 30, 60)
TABLE_METHODS = ("gsp", "sparse_projection", "l2", "linf", "double_cusum")


def seed_of(*parts) -> int:
    return zlib.crc32(json.dumps(parts).encode())


def replicates(spark: SparkSession, configs: Iterable[dict], reps: int, run: Callable, shared=None) -> DataFrame:
    """run(config, rep, shared) -> rows of RUN, for every configuration and replicate; rows of work are dealt evenly."""
    configs = [json.dumps(c, sort_keys=True) for c in configs]
    sent = spark.sparkContext.broadcast(shared)
    slots = min(len(configs) * reps, 4 * spark.sparkContext.defaultParallelism) or 1
    work = spark.createDataFrame([(i, c) for i, c in enumerate(configs)], "i int, config string")
    work = work.select("i", "config", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    work = work.repartitionByRange(slots, F.xxhash64("i", "rep"))

    def go(batches):
        import pandas as pd

        names = [f.split()[0] for f in RUN.split(", ")]
        for pdf in batches:
            rows = [r for c, rep in zip(pdf["config"], pdf["rep"], strict=True) for r in run(json.loads(c), int(rep), sent.value)]
            out = pd.DataFrame(rows, columns=names)
            yield out.astype({"z_true": "Int64", "z_hat": "Int64"})

    return work.mapInPandas(go, RUN)


def _sine(v, theta) -> float:
    import numpy as np

    if v is None or not v.any():
        return 1.0
    return float(np.sqrt(max(0.0, 1 - (v @ theta) ** 2 / (theta @ theta))))


def noise_of(panel: DataFrame | None):
    """The matrix of a panel of the given tables that stands for simulated noise, or None; standardised, one row a series."""
    return None if panel is None else multi.as_matrix(scale.standardised(panel))[0]


def _with_steps(p: int, n: int, steps, seed: int, noise, draw):
    """Steps on normal noise, or on the times of the given noise in an order that draw gives."""
    if noise is None:
        return kernels.gaussian(p, n, steps, seed)
    x = noise[:, draw.permutation(n)]
    for z, theta in steps:
        x[:, z:] += theta[:, None]
    return x


def _drawn(c: dict, rep: int, groups, noise=None):
    """A panel for a configuration and replicate, and its jump vector; the groups that change are drawn."""
    import numpy as np

    seed = seed_of(c.get("data", c["id"]), rep)
    draw = np.random.default_rng(seed)
    chosen = draw.choice(len(groups), c["s"], replace=False)
    theta = kernels.step_vector(c["p"], groups, chosen, c["size"])
    return _with_steps(c["p"], c["n"], [(c["z"], theta)], seed, noise, draw), theta


def _direction_losses(c: dict, rep: int, noise):
    groups = kernels.windows(c["p"], c["block"], c["step"]) if c.get("step") else kernels.blocks(c["p"], c["block"])
    x, theta = _drawn(c, rep, groups, noise)
    x = x / kernels.row_scale(x)[:, None]
    least = min(map(len, groups))
    for name in c["methods"]:
        lam = c.get("multiplier", 0.5) * tuning.lambda_theory(c["n"], len(groups), least)
        z, stat, v = kernels.method(x, "gsp_columnwise" if name == "gsp" and c.get("step") else name, groups, lam)
        yield c["id"], rep, name, c["z"], z, _sine(v, theta), stat


def theory_validation(spark, n=1000, ps=(600, 1200, 2400), sizes=DYADIC, least=DIVISORS_OF_60, reps=100, k=60, s=3, panel: DataFrame | None = None) -> DataFrame:
    """Loss of direction against the group size: with k changing rows fixed, and with s changing groups fixed; theoretical level.

    Here and below a panel of the given tables takes the place of simulated noise, with its own numbers of series and times.
    """
    noise = noise_of(panel)
    if noise is not None:
        ps, n = (noise.shape[0],), noise.shape[1]
    configs = []
    for p in ps:
        for size in sizes:
            for b in least:
                if k % b == 0 and p % b == 0:
                    configs.append({"id": f"k|{p}|{size}|{b}", "p": p, "n": n, "z": int(0.4 * n), "size": size, "block": b, "s": k // b})
                if p // b >= s and p % b == 0:
                    configs.append({"id": f"s|{p}|{size}|{b}", "p": p, "n": n, "z": int(0.4 * n), "size": size, "block": b, "s": s})
    return replicates(spark, [c | {"methods": ["gsp"], "multiplier": 1.0} for c in configs], reps, _direction_losses, noise)


def lambda_sweep(spark, n=1000, z=400, s=3, group_counts=(10, 25), ps=(500, 1000), sizes=DYADIC, reps=100, panel: DataFrame | None = None) -> DataFrame:
    """Loss against the level's multiplier; the same data for all multipliers of a setting."""
    noise = noise_of(panel)
    if noise is not None:
        ps, n = (noise.shape[0],), noise.shape[1]
        z = int(0.4 * n)
    configs = [
        {"id": f"{p}|{g}|{size}|{m:.4f}", "data": f"{p}|{g}|{size}", "p": p, "n": n, "z": z, "size": size, "block": p // g, "s": s, "multiplier": m, "methods": ["gsp"]}
        for p in ps for g in group_counts for size in sizes for m in tuning.GRID
    ]
    return replicates(spark, configs, reps, _direction_losses, noise)


def direction_compare(spark, n=1000, p=1000, sizes=DYADIC, block=100, step=50, s=3, z=None, reps=100, panel: DataFrame | None = None) -> DataFrame:
    """Loss of the grouped detector and of the one without groups, for disjoint blocks and for overlapping windows."""
    noise = noise_of(panel)
    if noise is not None:
        p, n = noise.shape
    base = {"p": p, "n": n, "z": z or int(0.4 * n), "block": block, "methods": ["gsp", "sparse_projection"]}
    configs = [base | {"id": f"disjoint|{size}", "size": size, "s": s} for size in sizes]
    configs += [base | {"id": f"overlap|{size}", "size": size, "s": 1, "step": step} for size in sizes]
    return replicates(spark, configs, reps, _direction_losses, noise)


def location_compare(spark, n=1000, ps=(500, 1000, 2000), sizes=(0.25, 0.5, 1.0, 2.0, 4.0), group_count=10, s=3, z=None, reps=100, methods=TABLE_METHODS, panel: DataFrame | None = None) -> DataFrame:
    """Distance of the located from the true time for five detectors on the same data."""
    noise = noise_of(panel)
    if noise is not None:
        ps, n = (noise.shape[0],), noise.shape[1]
    configs = [
        {"id": f"{p}|{size}", "p": p, "n": n, "z": z or int(0.4 * n), "size": size, "block": p // group_count, "s": s, "methods": list(methods)} for p in ps for size in sizes
    ]
    return replicates(spark, configs, reps, _direction_losses, noise)


def _planted_draw(c: dict, rep: int, n: int, group_count: int):
    """(z, groups that change, order of the times)."""
    import numpy as np

    draw = np.random.default_rng(seed_of(c["id"], rep))
    z = int(draw.integers(n // 5, n - n // 5))
    return z, draw.choice(group_count, min(c["s"], group_count), replace=False), draw.permutation(n)


def _planted_run(c: dict, rep: int, shared):
    x, groups, lam = shared
    z, chosen, order = _planted_draw(c, rep, x.shape[1], len(groups))
    theta = kernels.step_vector(len(x), groups, chosen, c["size"])
    moved = x[:, order]
    moved[:, z:] += theta[:, None]
    for name in c["methods"]:
        found, stat, v = kernels.method(moved, name, groups, lam)
        yield c["id"], rep, name, z, found, _sine(v, theta), stat


def planted_compare(panel: DataFrame, groups: DataFrame, sizes=(0.5, 1.0, 2.0, 3.0), s=2, reps=20, methods=TABLE_METHODS) -> DataFrame:
    """The same comparison on a panel of the given tables: its times are permuted jointly and a change is planted.

    A panel beyond multi.REPLICATED_CELLS is dealt to slices of series; groups are disjoint there, and directions' losses are left out.
    """
    panel = relax.work_table(scale.standardised(panel), "panel")
    lam, disjoint, n = single.level(panel, groups, None)
    configs = [{"id": str(size), "size": size, "s": s, "methods": list(methods)} for size in sizes]
    if panel.count() > multi.REPLICATED_CELLS:
        if not disjoint:
            raise ValueError("a panel dealt to slices has no gsp for overlapping groups")
        return _planted_wide(panel, groups, configs, reps, n, lam)
    x, ids = multi.as_matrix(panel)
    return replicates(panel.sparkSession, configs, reps, _planted_run, (x, multi.as_rows(groups, ids), lam))


def _planted_wide(panel: DataFrame, groups: DataFrame, configs: list[dict], reps: int, n: int, lam: float) -> DataFrame:
    count = groups.join(panel.select("series_id"), "series_id", "left_semi").select("group_id").distinct().count()
    variants, named = [], []
    for c in configs:
        for rep in range(reps):
            z, chosen, order = _planted_draw(c, rep, n, count)
            named.append((len(variants), c["id"], rep, z))
            variants.append((order, z, tuple(int(g) for g in chosen), c["size"]))
    found = wide.detect_orders(panel, groups, variants, lam, tuple(configs[0]["methods"]))
    told = panel.sparkSession.createDataFrame(named, "i int, config_id string, rep int, z_true long")
    loss = F.lit(None).cast("double").alias("loss")
    return found.join(F.broadcast(told), "i").select("config_id", "rep", "method", "z_true", F.col("z").alias("z_hat"), loss, "stat")


def _multi_run(c: dict, rep: int, shared):
    import numpy as np

    xi, noise = shared
    groups = kernels.blocks(c["p"], c["block"])
    seed = seed_of(c["data"], rep)
    draw = np.random.default_rng(seed)
    chosen = draw.choice(len(groups), c["s"], replace=False)
    n = c["n"]
    truth = [n // 4, n // 2, 3 * n // 4]
    steps = [(z, kernels.step_vector(c["p"], groups, chosen, c["size"] * m)) for z, m in zip(truth, (1, 1.5, 2), strict=True)]
    x = _with_steps(c["p"], n, steps, seed, noise, draw)
    x = x / kernels.row_scale(x)[:, None]
    lam = tuning.lambda_practical(n, len(groups), c["block"])
    pairs = np.sort(draw.integers(0, n + 1, (4 * c["intervals"], 2)), axis=1)
    pairs = pairs[pairs[:, 1] - pairs[:, 0] >= 2][: c["intervals"]]
    for name in ("gsp", "sparse_projection"):
        found = kernels.recurse(kernels.interval_candidates(x, pairs.tolist(), multi.finder(name, groups, lam)), n, xi[f"{c['p']}|{name}"])
        score = kernels.ari(truth, [f[0] for f in found], n)
        yield c["id"], rep, f"{name}_ari", None, len(found), score, None
        for f in found:
            yield c["id"], rep, name, None, f[0], None, f[1]


def multi_compare(spark, n=1200, settings=((500, 50), (1000, 100)), sparsity=(3, 10), sizes=(0.6, 0.8, 1.0, 1.2, 1.4), reps=100, intervals=1000, nulls=1000, panel: DataFrame | None = None, group_count=10) -> DataFrame:
    """Three changes: adjusted Rand index (loss of rows <method>_ari) and located times of both projection detectors.

    On a panel of the given tables with group_count groups, thresholds come from joint permutations of its times.
    """
    noise = noise_of(panel)
    if noise is not None:
        settings, n = ((noise.shape[0], group_count),), noise.shape[1]
        standard = relax.work_table(scale.standardised(panel), "panel")
        series = standard.select("series_id").distinct()
        numbered = series.select((F.row_number().over(Window.orderBy("series_id")) - 1).alias("row"), "series_id")
    xi = {}
    for p, g in settings:
        block = p // g
        for name in ("gsp", "sparse_projection"):
            lam = tuning.lambda_practical(n, g, block)
            if noise is None:
                xi[f"{p}|{name}"] = multi.xi_monte_carlo(spark, p, n, kernels.blocks(p, block), lam, nulls, name)
            else:
                groups = numbered.select(F.expr(f"row div {block}").alias("group_id"), "series_id")
                xi[f"{p}|{name}"] = multi.xi_permuted(standard, groups, lam, nulls, name)
    configs = [
        {"id": f"{p}|{s}|{size}", "data": f"{p}|{s}|{size}", "p": p, "n": n, "block": p // g, "s": s, "size": size, "intervals": intervals}
        for p, g in settings for s in sparsity for size in sizes
    ]
    return replicates(spark, configs, reps, _multi_run, (xi, noise))


def real_series(panel: DataFrame, groups: DataFrame, intervals: int = 1000, nulls: int = 1000, seed: str = "real") -> DataFrame:
    """Change points of a panel of the given tables, with a threshold from joint permutations of its times."""
    panel = scale.standardised(panel).persist()
    xi = multi.xi_permuted(panel, groups, reps=nulls)
    return multi.detect_multiple(panel, groups, xi, intervals=intervals, seed=seed)


def null_statistics(spark, p: int, n: int, block: int, delta: float, reps: int = 1000) -> DataFrame:
    """(stat): the dual norm of the CUSUM of change-free normal panels."""
    groups = kernels.blocks(p, block)

    def run(c, rep, _):
        yield c["id"], rep, "dual_norm", None, None, None, kernels.dual_norm(kernels.cusum(kernels.gaussian(p, n, [], seed_of("null", rep))), groups)

    return replicates(spark, [{"id": str(delta)}], reps, run)


def supplier_groups(spark: SparkSession, sf: str) -> DataFrame:
    """Suppliers by region."""
    nations = panels.table(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    suppliers = panels.table(spark, sf, "supplier").select("s_suppkey", "s_nationkey")
    return gr.from_table(suppliers.join(nations, suppliers["s_nationkey"] == nations["n_nationkey"]), "s_suppkey", "n_regionkey")
