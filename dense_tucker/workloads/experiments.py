"""The experiments: overall time, load, communication, scaling, error and ablations, on tables and generated metadata."""

from __future__ import annotations

import hashlib
import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from math import prod

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.meta import NAMED, TensorMeta
from ..operators import blocks as B
from ..operators import decompose as D
from ..operators import measures as M
from ..operators.stage_metrics import observed
from ..plans import grids as G
from ..plans import optimal, trees
from ..plans.planner import STRATEGIES, strategy
from ..sources import benchmark, builders
from . import planning

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
_KS = [1, 10, 25, 40, 50, 60, 75, 90, 99]
_SPECS = builders.specs()


def timed_sweeps(spark: SparkSession, cells: DataFrame, meta: TensorMeta, p: int, names=tuple(STRATEGIES), policy: str = "frozen") -> list[tuple]:
    """One measured sweep under each strategy on the same random factors."""
    rows = []
    for name in names:
        made = strategy(meta, p, name)
        t = B.distribute(cells, meta.L, made.scheme.grids[0]).persist()
        t.df.count()
        seen = D.Measured()
        D.sweep(t, D.Decomposition(meta, np.zeros(meta.K), D.random_init(meta)), made, policy, measured=seen)
        t.unpersist()
        rows.append((meta.name, name, float(made.load), float(made.volume), seen.wall_s, seen.ttm_s, seen.comm_s, seen.svd_s, seen.core_s, seen.ttms, seen.regrids, float(seen.moved_elements), seen.peak_live, seen.shuffle_bytes, seen.shuffle_task_s, seen.compute_task_s))
    return rows


_TIMED = "tensor_id string, strategy string, load double, volume double, wall_s double, ttm_s double, comm_s double, svd_s double, core_s double, ttms int, regrids int, moved double, peak_live int, shuffle_bytes long, shuffle_task_s double, compute_task_s double"


def _table_meta(spark, d, name, K=None) -> TensorMeta:
    return TensorMeta(builders.lengths(spark, d, name), K or _SPECS[name].K, name)


_OVERALL = "tensor_id string, strategy string, load double, volume double, wall_s double, compute_task_s double, comm_task_s double, shuffle_bytes double"
#: Benchmark inputs that the registered queries run (`python -m dense_tucker.workloads.overall` runs more of them).
OVERALL_METAS = 2


def overall_sweeps(spark: SparkSession, metas: list[TensorMeta], p: int, names=tuple(STRATEGIES), cells: DataFrame | None = None) -> list[tuple]:
    """One sweep for each input (random cells, unless some are given) and strategy, nothing forced in between: wall time, and the task seconds and bytes that Spark's stages report."""
    rows = []
    for meta in metas:
        for name in names:
            made = strategy(meta, p, name)
            t = B.distribute(builders.random_cells(spark, meta.L) if cells is None else cells, meta.L, made.scheme.grids[0]).persist()
            t.df.count()
            with observed(spark) as stages:
                began = time.perf_counter()
                D.sweep(t, D.Decomposition(meta, np.zeros(meta.K), D.random_init(meta)), made, "frozen")
                wall = time.perf_counter() - began
            t.unpersist()
            rows.append((meta.name, name, float(made.load), float(made.volume), wall, stages.task_s - stages.shuffle_s, stages.shuffle_s, float(stages.shuffle_bytes)))
    return rows


def shrunk(n: int, count: int, most: int = 60_000) -> list[TensorMeta]:
    """Inputs of the generated benchmark, drawn by a hash of their names, with lengths and core divided alike until at most `most` cells are left; no two alike.

    A mode of 20 with a ratio of 1.25 keeps a core of at least 2, so that 32 blocks fit.
    """
    out: dict[tuple, TensorMeta] = {}
    for meta in sorted(benchmark.enumerate_metas(n, "pairs"), key=lambda m: hashlib.md5(f"{m.L}{m.K}".encode()).hexdigest()):
        share = (most / meta.cardinality()) ** (1 / n)
        L = tuple(max(4, round(x * share)) for x in meta.L)
        K = tuple(max(2, min(length, round(length * k / x))) for length, x, k in zip(L, meta.L, meta.K, strict=True))
        out.setdefault((L, K), TensorMeta(L, K, f"{n}d-{len(out)}"))
        if len(out) == count:
            break
    return list(out.values())


def overall_curve(rows: DataFrame) -> DataFrame:
    """strategy, k, and the kth percentile of each time and of the bytes over those of the optimal tree under dynamic grids."""
    out = None
    for metric in ("wall_s", "compute_task_s", "comm_task_s", "shuffle_bytes"):
        curve = M.percentile_curve(M.normalise(rows, metric), f"{metric}_ratio", [0, 25, 50, 60, 75, 100]).withColumnRenamed("t", f"{metric}_ratio")
        out = curve if out is None else out.join(curve, ["strategy", "k"])
    return out


def _overall(s, n: int) -> DataFrame:
    return overall_curve(s.createDataFrame(overall_sweeps(s, shrunk(n, OVERALL_METAS), 32), _OVERALL))


def w1_overall_5d(s, d):
    return _overall(s, 5)


def w1_overall_6d(s, d):
    return _overall(s, 6)


def w1_overall_tables(s, d):
    """The same on the tensors of the tables with five and six modes."""
    rows = [r for name in ("ta", "tc") for r in overall_sweeps(s, [_table_meta(s, d, name)], 4, cells=builders.filled_cells(s, d, name))]
    return M.normalise(s.createDataFrame(rows, _OVERALL), "wall_s")


def w2_real_meta_load(s, d):
    return M.normalise(M.plan_all(benchmark.meta_frame(s, list(NAMED.values()))), "load").select("tensor_id", "strategy", "load", "load_ratio")


def w2_real_meta_volume(s, d):
    return M.normalise(M.plan_all(benchmark.meta_frame(s, list(NAMED.values()))), "volume").select("tensor_id", "strategy", "volume", "relative_volume", "volume_ratio")


def w2_real_scaled_run(s, d):
    metas = []
    for name in ("HCCI", "TJLR", "SP"):
        m = NAMED[name]
        L = tuple(max(4, x // 16) if x > 16 else min(x, 4) for x in m.L)
        metas.append(TensorMeta(L, tuple(max(1, min(n, round(n * k / x))) for n, k, x in zip(L, m.K, m.L, strict=True)), f"{name}/16"))
    rows = []
    for meta in metas:
        rows += overall_sweeps(s, [meta], 32)
    out = s.createDataFrame(rows, _OVERALL)
    for metric in ("wall_s", "compute_task_s", "shuffle_bytes"):
        out = M.normalise(out, metric)
    return out


def _planned(s, n: int) -> DataFrame:
    return M.plan_all(benchmark.benchmark(s, n))


def _load_curve(s, n):
    return M.percentile_curve(M.normalise(_planned(s, n), "load"), "load_ratio", _KS)


def _subsets(s, d, n: int) -> list[TensorMeta]:
    """All n-column subsets of the categorical columns with each single ratio; lengths from the tables."""
    from itertools import combinations

    lengths: dict[str, int] = {}
    for table, names in {"lineitem": ["l_returnflag", "l_linestatus", "l_linenumber", "l_discount", "l_tax"], "orders": ["o_orderpriority", "o_orderstatus"], "part": ["p_brand", "p_type", "p_size"], "customer": ["c_mktsegment"]}.items():
        row = builders.read(s, d, table).agg(*[F.count_distinct(c) for c in names]).first()
        lengths |= dict(zip(names, map(int, row), strict=True))
    out = []
    for pick in combinations(sorted(lengths), n):
        for ratio in (1.25, 2.0, 5.0):
            L = tuple(lengths[c] for c in pick)
            out.append(TensorMeta(L, tuple(max(1, -(-int(x * 100) // int(ratio * 100))) for x in L), "+".join(pick) + f"/{ratio}"))
    return out


def w3_load_tables(s, d):
    metas = [m for n in (5, 6) for m in _subsets(s, d, n)]
    return M.percentile_curve(M.normalise(M.plan_all(benchmark.meta_frame(s, metas, 8)), "load"), "load_ratio", _KS)


def _volume(s, n):
    both = M.plan_all(benchmark.benchmark(s, n), ("opt_static", "opt_dynamic"))
    return M.normalise(both, "volume").where("strategy = 'opt_static'")


def w4_volume_static_vs_dynamic(s, d):
    out = None
    for n in (5, 6):
        v = _volume(s, n).withColumn("strategy", F.lit(f"{n}d"))
        part = M.percentile_curve(v, "volume_ratio", _KS).join(M.gain_share(v, "volume_ratio", 3.0).withColumnRenamed("share", "share_ge_3"), "strategy")
        out = part if out is None else out.union(part)
    return out


def w4_comm_time(s, d):
    timed = s.createDataFrame(timed_sweeps(s, builders.filled_cells(s, d, "tj"), _table_meta(s, d, "tj"), 8, ("opt_static", "opt_dynamic")), _TIMED)
    return M.normalise(timed, "moved")


#: The published inputs of greatest and least overall gain, a fifth as long in each mode.
_FIFTH = [TensorMeta((80, 20, 20, 10, 4), (16, 16, 2, 8, 2), "greatest/5"), TensorMeta((80, 80, 4, 4, 4), (64, 8, 2, 2, 2), "least/5")]


def w4_shuffle_bytes(s, d):
    """Static beside dynamic grids of 32 blocks on the optimal tree: planned elements beside the bytes that Spark shuffles in a sweep."""
    both = ("opt_static", "opt_dynamic")
    rows = timed_sweeps(s, builders.filled_cells(s, d, "tj"), _table_meta(s, d, "tj"), 32, both)
    for meta in _FIFTH:
        rows += timed_sweeps(s, builders.random_cells(s, meta.L), meta, 32, both)
    out = s.createDataFrame(rows, _TIMED)
    for metric in ("volume", "moved", "shuffle_bytes", "wall_s"):
        out = M.normalise(out, metric)
    return out


def w5_scaling(s, d):
    """The same sweep of the largest table tensor with more blocks: time by P (a withdrawn study; only the shape of the curve is of use)."""
    rows = []
    meta = _table_meta(s, d, "tj")
    cells = builders.filled_cells(s, d, "tj").persist()
    for p in (1, 2, 4, 8):
        t = timed_sweeps(s, cells, meta, p, ("opt_dynamic",))[0]
        rows.append((p, t[4], t[5], t[6]))
    cells.unpersist()
    return s.createDataFrame(rows, "p int, wall_s double, ttm_s double, comm_s double")


#: Bytes of a block of cells that are cut along the longest mode.
_BLOCK_BYTES = 32 << 20


def _side_by_side(spark: SparkSession, make, items: list) -> list:
    """Answers in order; the jobs of several small tensors share the executors."""
    with ThreadPoolExecutor(len(items)) as pool:
        return list(pool.map(inheritable_thread_target(spark)(make), items))


def _squeezed_table(s, d, name: str, grid: tuple[int, ...]) -> tuple[TensorMeta, B.Blocked]:
    """A table's tensor with its overlong mode squeezed. That mode alone is cut, into blocks of bounded size, where there is one."""
    meta = _table_meta(s, d, name)
    long = next((m for m in range(meta.n) if meta.L[m] > meta.fiber_count(m)), None)
    if long is not None:
        q = min(meta.L[long], max(prod(grid), -(-8 * meta.cardinality() // _BLOCK_BYTES)))
        grid = tuple(q if m == long else 1 for m in range(meta.n))
    return meta, D.squeezed(B.distribute(builders.filled_cells(s, d, name), meta.L, grid), meta)[0]


def w7_error_vs_sweeps(s, d):
    def run(item):
        name, p = item
        made = strategy(_table_meta(s, d, name), p, "opt_dynamic")
        meta, t = _squeezed_table(s, d, name, made.scheme.grids[0])
        small = TensorMeta(t.shape, tuple(map(min, meta.K, t.shape)), name)
        t = B.regrid(t, made.scheme.grids[0]).persist()
        start = D.seq_init(t, small, optimal.seq_init_order(meta)[0])

        def sweeps(policy):
            h = D.sweep_until(t, start, replace(made, meta=small), 0.0, 2, policy)
            return [(name, policy, i, float(e), h.error_increased) for i, e in enumerate(h.errors)]

        rows = sum(_side_by_side(s, sweeps, ["latest", "frozen"]), [])
        t.unpersist()
        return rows

    rows = sum(_side_by_side(s, run, [("ta", 4), ("tb", 8), ("tc", 4), ("te", 8)]), [])
    return s.createDataFrame(rows, "tensor string, policy string, sweep int, rel_error double, error_increased boolean")


def w8_compression(s, d):
    def run(name):
        full, t = _squeezed_table(s, d, name, (1, 4, 1))
        t.persist()

        def at(ratio):
            meta = TensorMeta(full.L, tuple(max(1, round(n / ratio)) for n in full.L), name)
            dec = D.seq_init(t, TensorMeta(t.shape, tuple(map(min, meta.K, t.shape)), name), optimal.seq_init_order(meta)[0])
            return (name, ratio, meta.compression_rate(), meta.compression_rate(True), D.errors(t, dec, "norms")["rel_error"])

        rows = _side_by_side(s, at, [1.25, 2.0, 5.0, 10.0])
        t.unpersist()
        return rows

    rows = sum(_side_by_side(s, run, ["tb", "te"]), [])
    return s.createDataFrame(rows, "tensor string, ratio double, rate double, rate_with_factors double, rel_error double")


def w9_ablation(s, d):
    """What each choice is worth: reuse policy (load), regrid target and gridding (volume)."""
    rows = []
    for m in NAMED.values():
        best = optimal.optimal_tree(m)[1]
        for policy in ("always_reuse", "no_reuse"):
            rows.append((m.name, f"tree:{policy}", optimal.optimal_tree(m, policy)[1] / best))
        tree = optimal.optimal_tree(m)[0]
        full = G.best_dynamic_scheme(tree, m, 32).total
        rows.append((m.name, "regrid:children_only", G.best_dynamic_scheme(tree, m, 32, "children_only").total / full))
        rows.append((m.name, "grid:static", G.best_static_grid(tree, m, 32)[1] / full))
    return s.createDataFrame(rows, "tensor_id string, choice string, ratio double")


def w9_policies(s, d):
    rows = []
    meta = _table_meta(s, d, "tb")
    made = strategy(meta, 8, "opt_dynamic")
    t = B.distribute(builders.filled_cells(s, d, "tb"), meta.L, made.scheme.grids[0])
    for policy in ("frozen", "latest"):
        began = time.perf_counter()
        dec = D.sweep(t, D.initial(t, meta, "random"), made, policy)
        rows.append((policy, D.errors(t, dec, "norms")["rel_error"], time.perf_counter() - began))
    return s.createDataFrame(rows, "policy string, rel_error double, wall_s double")


def _measure(kind: str):
    def run(s, d):
        df = M.normalise(_planned(s, 5), "load")
        if kind == "extremes":
            return M.extreme_gains(df, "load_ratio")
        if kind == "share":
            return M.gain_share(df, "load_ratio", 1.5)
        if kind == "best_prior":
            prior = df.where(F.col("strategy").isin("chain_K", "chain_h", "balanced")).groupBy("tensor_id").agg(F.min("load_ratio").alias("gain"))
            return prior.agg(F.max("gain").alias("greatest"), F.median("gain").alias("median"), F.min("gain").alias("least"))
        named = M.normalise(M.plan_all(benchmark.meta_frame(s, list(NAMED.values()))), "load")
        return M.dominates(named, "load_ratio").join(named.groupBy("strategy").agg(F.min("load_ratio").alias("least_ratio")), "strategy")

    return run


#: Closed-form loads of the natural balanced and chain trees over all inputs of the 'lengths' rule, for SQL.
def _curve_metas() -> list[TensorMeta]:
    return [TensorMeta(m.L, m.K, f"c{i}") for i, m in enumerate(benchmark.enumerate_metas(5, "lengths"))]


def chain_gain_curve(s, d):
    """Percentiles of the natural chain's load over the h-ordered chain's."""
    rows = [(m.name, name, trees.tree_load(trees.chain_tree(trees.mode_order(m, by)), m, True)) for m in _curve_metas() for name, by in (("chain", "natural"), ("chain_h", "h"))]
    df = s.createDataFrame(rows, "tensor_id string, strategy string, load double")
    out = M.percentile_curve(M.normalise(df, "load", "chain_h"), "load_ratio", [10, 50, 90])
    return out.withColumn("t", F.round("t", 6))


def _chain_curve_sql() -> str:
    metas = _curve_metas()
    values = "(values " + ", ".join(f"('{m.name}', {k}, {m.L[k]}.0::double, {m.K[k]}.0::double)" for m in metas for k in range(5)) + ") as modes(tensor_id, mode, L, K)"
    load = "select f.tensor_id, sum(K * coalesce((select product(b.K / b.L) from {0} b where b.tensor_id = f.tensor_id and b.r < a.r and b.mode <> f.mode), 1.0)) as load from {0} a join (select tensor_id, mode from {0}) f on a.tensor_id = f.tensor_id and a.mode <> f.mode group by 1"
    return (
        f"with m as (select * from {values}), n as (select *, mode as r from m), h as (select *, row_number() over (partition by tensor_id order by K / L, mode) as r from m), "
        f"ln as ({load.format('n')}), lh as ({load.format('h')}), both_ as (select 'chain' as strategy, ln.load / lh.load as ratio from ln join lh using (tensor_id) union all select 'chain_h', 1.0 from lh) "
        "select strategy, unnest([10, 50, 90]) as k, round(unnest(quantile_cont(ratio, [0.1, 0.5, 0.9])), 6) as t from both_ group by strategy"
    )


def planner_statistics(s, d):
    """What planning the published inputs costs: states and lookups of the tree search, grids looked at, milliseconds."""
    rows = []
    for m in NAMED.values():
        for name in STRATEGIES:
            stats = strategy(m, 32, name).stats
            rows.append((m.name, name, stats.get("dp_states"), stats.get("dp_lookups"), stats["grids_scanned"], 1e3 * stats["planner_s"]))
    return s.createDataFrame(rows, "tensor_id string, strategy string, dp_states bigint, dp_lookups bigint, grids_scanned bigint, planner_ms double")


QUERIES |= {
    "w1_overall_5d": w1_overall_5d,
    "w1_overall_6d": w1_overall_6d,
    "w1_overall_tables": w1_overall_tables,
    "w2_real_meta_load": w2_real_meta_load,
    "w2_real_meta_volume": w2_real_meta_volume,
    "w2_real_scaled_run": w2_real_scaled_run,
    "w3_load_5d": lambda s, d: _load_curve(s, 5),
    "w3_load_6d": lambda s, d: _load_curve(s, 6),
    "w3_load_tables": w3_load_tables,
    "w4_volume_static_vs_dynamic": w4_volume_static_vs_dynamic,
    "w4_comm_time": w4_comm_time,
    "w4_shuffle_bytes": w4_shuffle_bytes,
    "w5_scaling": w5_scaling,
    "w7_error_vs_sweeps": w7_error_vs_sweeps,
    "w8_compression": w8_compression,
    "w9_ablation": w9_ablation,
    "w9_policies": w9_policies,
    "planner_statistics": lambda s, d: planner_statistics(s, d),
    "strategy_table_5d": lambda s, d: _planned(s, 5).drop("planner_s"),
    "strategy_table_6d": lambda s, d: _planned(s, 6).drop("planner_s"),
    "measure_extreme_gains": _measure("extremes"),
    "measure_gain_share": _measure("share"),
    "measure_dominates": _measure("dominates"),
    "measure_best_prior": _measure("best_prior"),
    "norm_load_curve": chain_gain_curve,
}
ORACLES |= {
    "measure_dominates": f"select strategy, min(load_ratio) as least_ratio, bool_and(load_ratio >= 1 - 1e-12) as dominated from ({planning.named_loads_sql(list(NAMED.values()))}) group by strategy",
    "norm_load_curve": _chain_curve_sql(),
    "w2_real_meta_load": planning.named_loads_sql(list(NAMED.values())),
    "w2_real_meta_volume": planning.named_volumes_sql(list(NAMED.values())),
}


def w6_grid_counts(s, d):
    return s.createDataFrame([(e, n, G.count_grids(2**e, n)) for e in (5, 10, 20) for n in range(5, 11)], "e int, n int, grids bigint")


QUERIES["w6_grid_counts"] = w6_grid_counts
ORACLES["w6_grid_counts"] = "select e::int as e, n::int as n, round(product((e + n - i)::double / i))::bigint as grids from (select unnest([5, 10, 20]) as e), (select unnest(range(5, 11)) as n), lateral (select unnest(range(1, n)) as i) group by e, n"
