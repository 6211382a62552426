"""Initial decompositions, refining sweeps under a plan, errors and measured sweeps."""

from __future__ import annotations

import re
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..model.decomposition import Decomposition
from ..model.meta import TensorMeta
from ..plans import optimal
from ..plans.planner import Plan, plan_seq_init
from ..plans.trees import Node
from . import blocks as B
from .stage_metrics import StageTotals, observed


def random_init(meta: TensorMeta, seed: int = 1) -> list[np.ndarray]:
    rng = np.random.default_rng(seed)
    return [B.fix_signs(np.linalg.qr(rng.normal(size=(n, k)))[0]) for n, k in zip(meta.L, meta.K, strict=True)]


def project_core(t: B.Blocked, factors: list[np.ndarray], order: list[int] | None = None) -> np.ndarray:
    """Tensor times all transposed factors, those that shrink most first."""
    order = order or sorted(range(len(factors)), key=lambda m: factors[m].shape[1] / factors[m].shape[0])
    for m in order:
        t = B.ttm(_fit_grid(t, m, factors[m].shape[1]), m, factors[m].T)
    return B.collect_array(t)


def _fit_grid(t: B.Blocked, mode: int, rows: int) -> B.Blocked:
    return B.regrid(t, B._whole_mode_grid(t, mode)) if t.grid[mode] > rows else t


def seq_init(t: B.Blocked, meta: TensorMeta, order: list[int] | None = None, solver: str = "auto") -> Decomposition:
    """Sequentially truncated: each new factor shrinks the tensor before the next is made."""
    order = order or optimal.seq_init_order(meta)[0]
    now, factors, energies = t, [np.zeros((0, 0))] * meta.n, {}
    for m in order:
        f, sigma = B.left_svd(now, m, meta.K[m], solver)
        factors[m], energies[m] = f, sigma**2
        now = B.ttm(_fit_grid(now, m, meta.K[m]), m, f.T)
    return Decomposition(meta, B.collect_array(now), factors, energies=energies)


def squeezed(t: B.Blocked, meta: TensorMeta) -> tuple[B.Blocked, TensorMeta]:
    """The tensor with every overlong mode squeezed, and its sizes: errors are those of the tensor itself (a core length beyond the columns keeps all)."""
    for m in range(meta.n):
        t = B.squeeze(t, m)
    return t, TensorMeta(t.shape, tuple(map(min, meta.K, t.shape)), meta.name)


def planned_seq_init(t: B.Blocked, meta: TensorMeta, p: int) -> Decomposition:
    """seq_init under its own planned order and grids."""
    order, scheme = plan_seq_init(meta, p)
    return seq_init(B.regrid(t, scheme.grids[0]), meta, order)


def hosvd_init(t: B.Blocked, meta: TensorMeta, solver: str = "auto") -> Decomposition:
    """Every factor from the whole tensor."""
    factors = [B.left_svd(t, m, meta.K[m], solver)[0] for m in range(meta.n)]
    return Decomposition(meta, project_core(t, factors), factors)


def initial(t: B.Blocked, meta: TensorMeta, how: str = "sequential", given: list[np.ndarray] | None = None) -> Decomposition:
    if how == "sequential":
        return seq_init(t, meta)
    if how == "hosvd":
        return hosvd_init(t, meta)
    factors = given if how == "given" else random_init(meta)
    return Decomposition(meta, project_core(t, factors), list(factors))


def squared_norm(t: B.Blocked) -> float:
    return B.squared_error(t, np.zeros((1,) * len(t.shape)), [np.zeros((n, 1)) for n in t.shape])["norm"]


def errors(t: B.Blocked, dec: Decomposition, how: str = "full", norm: float | None = None) -> dict[str, float]:
    """rel_error (gap over norm), rmse and nrmse_range; how='norms' uses the norms of tensor (given, or taken once) and core alone."""
    if how == "norms":
        norm = squared_norm(t) if norm is None else norm
        gap = max(0.0, norm - float((dec.core**2).sum()))
        return {"rel_error": float(np.sqrt(gap / norm)) if norm else 0.0}
    s = B.squared_error(t, dec.core, dec.factors)
    rmse = float(np.sqrt(s["gap"] / s["n"]))
    span = s["high"] - s["low"]
    return {"rel_error": float(np.sqrt(s["gap"] / s["norm"])) if s["norm"] else 0.0, "rmse": rmse, "nrmse_range": rmse / span if span else 0.0}


@dataclass
class Measured:
    """Times of one sweep in seconds; what moves is in elements, as Spark shuffles it.

    `ttm`, `regrid` and `svd` are the totals of the stages that made the products, changed the grids and made the factors (with the
    regrids that their Gram matrices need, gram_moved elements; no plan counts these); reading them takes aside_s, which
    wall_s leaves out.
    """

    wall_s: float = 0.0
    ttm_s: float = 0.0
    comm_s: float = 0.0
    svd_s: float = 0.0
    core_s: float = 0.0
    aside_s: float = 0.0
    ttms: int = 0
    regrids: int = 0
    peak_live: int = 0
    moved_elements: int = 0
    gram_moved: int = 0
    node_s: dict[int, float] = field(default_factory=dict)
    ttm: StageTotals = field(default_factory=StageTotals)
    regrid: StageTotals = field(default_factory=StageTotals)
    svd: StageTotals = field(default_factory=StageTotals)

    @property
    def shuffle_bytes(self) -> int:
        return self.ttm.shuffle_bytes + self.regrid.shuffle_bytes

    @property
    def shuffle_task_s(self) -> float:
        """Seconds that tasks spent writing shuffle files and waiting for blocks."""
        return self.ttm.shuffle_s + self.regrid.shuffle_s

    @property
    def compute_task_s(self) -> float:
        """Seconds of the product stages' tasks without their shuffles."""
        return self.ttm.task_s - self.ttm.shuffle_s


def sweep(t: B.Blocked, dec: Decomposition, plan: Plan, factor_policy: str = "frozen", solver: str = "auto", measured: Measured | None = None) -> Decomposition:
    """One refinement along the plan's tree, depth first.

    frozen: all products use the factors given, so every shared product is exact for all factors below it.
    latest: products use the newest factors; in depth-first order this is an exact alternating update on any
    valid tree, and the error cannot rise. With `measured` every node is forced and timed on its own. The tensor under the plan's
    first grid is kept while the sweep runs.
    """
    if factor_policy not in ("frozen", "latest"):
        raise ValueError(factor_policy)
    began = time.perf_counter()
    old, new = list(dec.factors), list(dec.factors)
    energies: dict[int, np.ndarray] = {}
    grids = plan.scheme.grids
    start = B.regrid(t, grids[0])
    own = not start.df.is_cached
    if own:
        start.persist()
    last: list = [None]
    counter = {"node": 0, "live": 0}

    def visit(node: Node, x: B.Blocked) -> None:
        number = counter["node"]
        counter["node"] += 1
        if node.kind == "leaf":
            at = time.perf_counter()
            if measured:
                with observed(x.df.sparkSession) as stages:
                    f, sigma = B.left_svd(x, node.mode, plan.meta.K[node.mode], solver)
                    done = time.perf_counter()
                measured.svd_s += done - at
                measured.svd += stages
                measured.aside_s += time.perf_counter() - done
                measured.gram_moved += int(np.prod(x.shape, dtype=object)) if x.grid[node.mode] > 1 else 0
            else:
                f, sigma = B.left_svd(x, node.mode, plan.meta.K[node.mode], solver)
            new[node.mode], energies[node.mode] = f, sigma**2
            last[0] = (node.mode, x)
            return
        made = x
        if node.kind == "mode":
            moved = B.regrid(x, grids[number])
            if measured and moved is not x:
                at = time.perf_counter()
                with observed(x.df.sparkSession) as stages:
                    moved.persist().df.count()
                    done = time.perf_counter()
                measured.comm_s += done - at
                measured.regrid += stages
                measured.aside_s += time.perf_counter() - done
                measured.regrids += 1
                measured.moved_elements += int(np.prod(x.shape, dtype=object))
            factor = (old if factor_policy == "frozen" else new)[node.mode]
            made = B.ttm(moved, node.mode, factor.T)
            if measured:
                at = time.perf_counter()
                with observed(x.df.sparkSession) as stages:
                    made.persist().df.count()
                    done = time.perf_counter()
                took = done - at
                measured.ttm += stages
                measured.aside_s += time.perf_counter() - done
                measured.ttm_s += took
                measured.node_s[number] = took
                measured.ttms += 1
                q = moved.grid[node.mode]
                if q > 1:
                    measured.moved_elements += q * int(np.prod(made.shape, dtype=object))
                if moved is not x:
                    moved.unpersist()
        shared = node.kind == "mode" and (len(node.children) > 1 or measured is not None)
        if shared:
            made.persist()
            counter["live"] += 1
            if measured:
                measured.peak_live = max(measured.peak_live, counter["live"])
        for child in node.children:
            visit(child, made)
        if shared:
            made.unpersist()
            counter["live"] -= 1

    visit(plan.tree, start)
    at = time.perf_counter()
    if factor_policy == "latest":  # the last leaf's input lacks only its own mode
        mode, x = last[0]
        core = B.collect_array(B.ttm(_fit_grid(x, mode, plan.meta.K[mode]), mode, new[mode].T))
    else:
        core = project_core(start, new)
    if measured:
        measured.core_s = time.perf_counter() - at
        measured.wall_s = time.perf_counter() - began - measured.aside_s
    if own:
        start.unpersist()
    return Decomposition(plan.meta, core, new, sweeps=dec.sweeps + 1, energies=energies)


@dataclass
class History:
    best: Decomposition
    errors: list[float]
    error_increased: bool


def sweep_until(t: B.Blocked, dec: Decomposition, plan: Plan, tol: float = 1e-6, max_sweeps: int = 10, factor_policy: str = "latest", solver: str = "auto", checkpoint: str | None = None) -> History:
    """Sweep until the error falls by less than tol; keeps the best decomposition and tells if the error ever rose.

    checkpoint: folder to which the decomposition is saved after every sweep; a later call with the same folder goes on from its last one.
    """
    spark, own = t.df.sparkSession, not t.df.is_cached
    if own:
        t.persist()
    norm = squared_norm(t)
    saved = saved_sweeps(spark, checkpoint) if checkpoint else []
    if saved:
        dec = Decomposition.load(spark, f"{checkpoint}/sweep={saved[-1]}")
    dec.error = errors(t, dec, "norms", norm)["rel_error"]
    history, best, rose = [dec.error], dec, False
    for _ in range(max_sweeps - len(saved)):
        dec = sweep(t, dec, plan, factor_policy, solver)
        dec.error = errors(t, dec, "norms", norm)["rel_error"]
        if checkpoint:
            dec.save(spark, f"{checkpoint}/sweep={dec.sweeps}")
        rose |= dec.error > history[-1] + 1e-9
        history.append(dec.error)
        if dec.error < best.error:
            best = dec
        if abs(history[-2] - history[-1]) < tol:
            break
    if own:
        t.unpersist()
    return History(best, history, rose)


def saved_sweeps(spark: SparkSession, folder: str) -> list[int]:
    """Numbers of the sweeps that were saved whole (their metadata is written last)."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{folder}/sweep=*/meta/_SUCCESS")
    found = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(path)
    return sorted(int(re.search(r"sweep=(\d+)", f.getPath().toString())[1]) for f in found or [])


def decompose(cells: DataFrame, meta: TensorMeta, plan: Plan, init: str = "sequential", sweeps: int = 1, factor_policy: str = "latest") -> History:
    """Cells to a refined decomposition under a plan."""
    t = B.distribute(cells, meta.L, plan.scheme.grids[0])
    return sweep_until(t, initial(t, meta, init), plan, 0.0, sweeps, factor_policy)
