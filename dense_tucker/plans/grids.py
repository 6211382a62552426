"""Processor grids: counting, listing, communication volume, the best static grid and the best changing ones."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import product
from math import comb, prod

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.meta import NoValidGrid, TensorMeta
from .trees import Node

Grid = tuple[int, ...]


def prime_factors(p: int) -> dict[int, int]:
    out: dict[int, int] = {}
    d = 2
    while p > 1:
        while p % d == 0:
            out[d] = out.get(d, 0) + 1
            p //= d
        d += 1
        if d * d > p > 1:
            out[p] = out.get(p, 0) + 1
            break
    return out


def count_grids(p: int, n: int) -> int:
    """Ways to write p as an ordered product of n factors."""
    return prod(comb(e + n - 1, n - 1) for e in prime_factors(p).values())


def enumerate_grids(p: int, n: int, most: tuple[int, ...] | None = None) -> np.ndarray:
    """All grids (rows) in ascending order; `most` bounds each mode's factor."""
    divisors = np.asarray([d for d in range(1, p + 1) if p % d == 0]) if p <= 1 << 16 else np.asarray(sorted(prod(c) for c in product(*[[q**i for i in range(e + 1)] for q, e in prime_factors(p).items()])))
    rows, left = np.zeros((1, 0), np.int64), np.asarray([p])
    for mode in range(n - 1):
        use = divisors if most is None else divisors[divisors <= most[mode]]
        fits = left[:, None] % use[None, :] == 0
        a, b = np.nonzero(fits)
        rows = np.concatenate([rows[a], use[b][:, None]], 1)
        left = left[a] // use[b]
    keep = left <= most[n - 1] if most is not None else np.ones(len(left), bool)
    return np.concatenate([rows[keep], left[keep][:, None]], 1)


def valid_grids(meta: TensorMeta, p: int) -> np.ndarray:
    """Grids that leave no block of any tensor empty: at most K blocks along each mode."""
    grids = enumerate_grids(p, meta.n, meta.K)
    if not len(grids):
        best = next(q for q in range(p - 1, 0, -1) if len(enumerate_grids(q, meta.n, meta.K)))
        raise NoValidGrid(f"no grid of {p} blocks fits core {meta.K}; {best} would")
    return grids


def ttm_volume(q: int, out_size: int, model: str = "paper") -> int:
    """Elements moved by one product with q blocks along its mode. spark: a shuffle sends every partial result."""
    if model == "spark":
        return q * out_size if q > 1 else 0
    return (q - 1) * out_size


def _table(tree: Node, meta: TensorMeta) -> list[tuple[int, int, int, int, int]]:
    """Inner nodes as (number, parent, mode, in, out), parents first."""
    out = []
    for number, parent, _, above, node in tree.walk():
        if node.kind == "mode":
            out.append((number, parent, node.mode, meta.size_after(above), meta.size_after(above | 1 << node.mode)))
    return out


def static_volumes(tree: Node, meta: TensorMeta, grids: np.ndarray, model: str = "paper") -> np.ndarray:
    """Volume of the tree under each grid (object integers: no overflow)."""
    total = np.zeros(len(grids), object)
    for _, _, mode, _, out in _table(tree, meta):
        q = grids[:, mode].astype(object)
        total = total + (q * out * (q > 1) if model == "spark" else (q - 1) * out)
    return total


def best_static_grid(tree: Node, meta: TensorMeta, p: int, model: str = "paper") -> tuple[Grid, int]:
    """Grid of least volume, the first in ascending order among equals."""
    grids = valid_grids(meta, p)
    volume = static_volumes(tree, meta, grids, model)
    at = int(np.argmin(volume.astype(float))) if len(volume) > 100_000 else min(range(len(volume)), key=volume.__getitem__)
    return tuple(int(x) for x in grids[at]), int(volume[at])


@dataclass(frozen=True)
class Scheme:
    """Grid of every node (by number; leaves keep their parent's) with its volume."""

    grids: dict[int, Grid]
    ttm: int
    regrid: int
    regrids: int

    @property
    def total(self) -> int:
        return self.ttm + self.regrid


def scheme_volume(tree: Node, meta: TensorMeta, grids: dict[int, Grid], model: str = "paper") -> Scheme:
    ttm = regrid = count = 0
    for number, parent, mode, size, out in _table(tree, meta):
        ttm += ttm_volume(grids[number][mode], out, model)
        if grids[number] != grids[parent]:
            regrid += size
            count += 1
    return Scheme(dict(grids), ttm, regrid, count)


def static_scheme(tree: Node, meta: TensorMeta, grid: Grid, model: str = "paper") -> Scheme:
    return scheme_volume(tree, meta, {number: grid for number, *_ in tree.walk()}, model)


def _spread(grid: Grid) -> tuple:
    """Order among equals: the most even grid first."""
    return max(grid) - min(grid), grid


def best_dynamic_scheme(tree: Node, meta: TensorMeta, p: int, target_rule: str = "full", model: str = "paper", prefer: str = "first") -> Scheme:
    """Grids of least volume for all nodes, bottom-up over (node, grid of the parent).

    Whether and where to a node regrids is decided once for each node, since the target does not depend on the
    parent's grid. target_rule 'full' weighs the node's own product too; 'children_only' leaves it out. The
    root never regrids. prefer: 'first' or 'balanced' among grids of equal volume.
    """
    grids = valid_grids(meta, p)
    as_object = grids.astype(object)
    rows = _table(tree, meta)
    below: dict[int, np.ndarray] = {}
    target: dict[int, int] = {}
    stay: dict[int, np.ndarray] = {}

    def least(values: np.ndarray) -> int:
        low = min(values)
        same = [i for i, v in enumerate(values) if v == low]
        return min(same, key=lambda i: _spread(tuple(grids[i].tolist()))) if prefer == "balanced" else same[0]

    for number, parent, mode, size, out in reversed(rows):
        q = as_object[:, mode]
        own = q * out * (q > 1) if model == "spark" else (q - 1) * out
        kids = below.get(number, np.zeros(len(grids), object))
        here = own + kids
        at = least(here if target_rule == "full" else kids)
        moved = size + here[at]
        stay[number] = here <= moved
        target[number] = at
        value = np.where(stay[number], here, moved)
        below[parent] = below.get(parent, np.zeros(len(grids), object)) + value
    start = least(below.get(0, np.zeros(len(grids), object)))
    chosen = {0: start}
    parents = {number: parent for number, parent, *_ in tree.walk()}
    for number, parent, *_ in rows:
        up = chosen[parent]
        chosen[number] = up if stay[number][up] else target[number]
    for number, parent in parents.items():
        if number not in chosen:
            chosen[number] = chosen[parent]
    return scheme_volume(tree, meta, {k: tuple(int(x) for x in grids[i]) for k, i in chosen.items()}, model)


def grid_frame(spark: SparkSession, meta: TensorMeta, p: int) -> DataFrame:
    """All valid grids as rows (q), listed by Spark mode by mode: only divisors of what is left and at most K go on."""
    divisors = [1]
    for prime, times in prime_factors(p).items():
        divisors = [d * prime**e for d in divisors for e in range(times + 1)]
    grids = spark.createDataFrame([([], p)], "q array<int>, rest bigint")
    for mode in range(meta.n):
        use = [d for d in sorted(divisors) if d <= meta.K[mode]] or [0]
        made = grids.select("q", "rest", F.explode(F.array(*map(F.lit, use))).alias("d")).where("d > 0 and rest % d = 0")
        grids = made.select(F.concat("q", F.array("d")).alias("q"), F.expr("rest div d").alias("rest"))
        if mode == 0:
            grids = grids.repartition("q")
    return grids.where("rest = 1").select("q")


def best_dynamic_scheme_distributed(spark: SparkSession, tree: Node, meta: TensorMeta, p: int, target_rule: str = "full", model: str = "paper") -> Scheme:
    """best_dynamic_scheme with one row for each grid: a column of values for each node, one aggregation for each node's target; the driver holds one grid for a node."""
    rows = _table(tree, meta)
    df = grid_frame(spark, meta, p)
    df.persist()
    number = "decimal(38, 0)"
    zero = F.lit(0).cast(number)
    below: dict[int, list[str]] = {}
    target: dict[int, tuple[Grid, int]] = {}
    for node, parent, mode, size, out in reversed(rows):
        q = F.col("q")[mode].cast(number)
        moved = F.when(q > 1, q).otherwise(zero) if model == "spark" else q - 1
        kids = sum((F.col(c) for c in below.get(node, [])), zero)
        df = df.withColumn(f"here{node}", (moved * F.lit(out).cast(number) + kids).cast(number))
        by = F.col(f"here{node}") if target_rule == "full" else kids
        best = df.agg(F.min_by(F.struct("q", f"here{node}"), F.struct(by, "q")).alias("b")).first()["b"]
        if best is None:
            raise NoValidGrid(f"no grid of {p} blocks fits core {meta.K}")
        target[node] = (tuple(best[0]), int(best[1]))
        df = df.withColumn(f"value{node}", F.least(F.col(f"here{node}"), F.lit(size + int(best[1])).cast(number)))
        below.setdefault(parent, []).append(f"value{node}")
    total = sum((F.col(c) for c in below.get(0, [])), zero)
    start = tuple(df.agg(F.min_by("q", F.struct(total, "q"))).first()[0])
    wanted = {start, *(g for g, _ in target.values())}
    picked = {tuple(r["q"]): r for r in df.where(F.array_join("q", ",").isin([",".join(map(str, g)) for g in wanted])).collect()}
    df.unpersist()
    chosen = {0: start}
    for node, parent, _, size, _ in rows:
        up = chosen[parent]
        chosen[node] = up if int(picked[up][f"here{node}"]) <= size + target[node][1] else target[node][0]
    for node, parent, *_ in tree.walk():
        chosen.setdefault(node, chosen.get(parent))
    return scheme_volume(tree, meta, chosen, model)


def enumerate_schemes(tree: Node, meta: TensorMeta, p: int) -> Iterator[Scheme]:
    """Every assignment of grids to root and inner nodes (small cases only)."""
    grids = [tuple(int(x) for x in g) for g in valid_grids(meta, p)]
    inner = [0, *[number for number, *_ in _table(tree, meta)]]
    parents = {number: parent for number, parent, *_ in tree.walk()}
    for pick in product(grids, repeat=len(inner)):
        chosen = dict(zip(inner, pick, strict=True))
        for number, parent in parents.items():
            if number not in chosen:
                chosen[number] = chosen[parent]
        yield scheme_volume(tree, meta, chosen)


def grid_balance(meta: TensorMeta, grid: Grid) -> dict:
    """Largest and mean number of cells of a block, and how many blocks are empty."""
    sizes = np.ones(1, object)
    for length, q in zip(meta.L, grid, strict=True):
        cut = np.asarray([(i + 1) * length // q - i * length // q for i in range(q)], object)
        sizes = (sizes[:, None] * cut[None, :]).ravel()
    return {"blocks": len(sizes), "largest": int(max(sizes)), "mean": float(sum(sizes)) / len(sizes), "empty": int(sum(s == 0 for s in sizes))}
