"""The engine's tensors: packed blocks under a processor grid, multiplied in Arrow batches with numpy.

A block is a row (bid, lo, shape, data): number in its grid, first coordinates, lengths and little-endian
float64 in C order. A product along a mode that the grid does not cut is narrow; one along a cut mode adds up
partial results by output block. Changing the grid sends each block's overlaps to the new blocks. Blocks are
meant to hold 16 to 64 MB, so tasks are bounded by the grid, not by the tensor.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass
from math import prod

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.grids import enumerate_grids

Grid = tuple[int, ...]
#: Longest mode whose length x length Gram matrix and eigenvectors the driver takes; longer ones go by subspace iteration.
GRAM_LENGTH = 4_000
#: Bytes of matrices that may be sent to every executor.
SHARED_BYTES = 512 << 20
SCHEMA = "bid int, lo array<int>, shape array<int>, data binary"
_ARROW = pa.schema([("bid", pa.int32()), ("lo", pa.list_(pa.int32())), ("shape", pa.list_(pa.int32())), ("data", pa.binary())])


def bounds(length: int, q: int) -> list[int]:
    """q + 1 cut points; block lengths differ by one at most."""
    return [i * length // q for i in range(q + 1)]


def _place(bid: int, grid: Grid) -> list[int]:
    out = []
    for q in reversed(grid):
        out.append(bid % q)
        bid //= q
    return out[::-1]


def _number(place, grid: Grid) -> int:
    n = 0
    for x, q in zip(place, grid, strict=True):
        n = n * q + x
    return n


def _row(bid: int, lo, array: np.ndarray) -> dict:
    return {"bid": bid, "lo": [int(x) for x in lo], "shape": list(array.shape), "data": np.ascontiguousarray(array, "<f8").tobytes()}


def _batch(rows: list[dict]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, schema=_ARROW)


def _blocks(batch: pa.RecordBatch) -> Iterator[tuple[int, list[int], np.ndarray]]:
    for r in batch.to_pylist():
        yield r["bid"], r["lo"], np.frombuffer(r["data"], "<f8").reshape(r["shape"])


def share(spark: SparkSession, value: np.ndarray | tuple):
    """Broadcast matrices of a checked size."""
    arrays = [value] if isinstance(value, np.ndarray) else [x for v in value for x in (v if isinstance(v, list) else [v])]
    size = sum(x.nbytes for x in arrays)
    if size > SHARED_BYTES:
        raise ValueError(f"{size} bytes of matrices for every executor; at most {SHARED_BYTES}")
    return spark.sparkContext.broadcast(value)


@dataclass
class Blocked:
    """A distributed tensor with its lengths and grid."""

    df: DataFrame
    shape: tuple[int, ...]
    grid: Grid

    def persist(self) -> Blocked:
        from pyspark import StorageLevel

        self.df.persist(StorageLevel.MEMORY_AND_DISK)
        return self

    def unpersist(self) -> None:
        self.df.unpersist()


def _by_block(df: DataFrame, grid: Grid):
    """Rows grouped by block, over about as many tasks as there are blocks: a kept tensor has no empty partitions to run over each time."""
    tasks = min(2 * prod(grid), int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return df.repartition(tasks, "bid").groupBy("bid")


def distribute(cells: DataFrame, shape: tuple[int, ...], grid: Grid) -> Blocked:
    """Pack cells (absent ones are zero, repeated ones are summed) under a grid: one shuffle, by block."""
    n = len(shape)
    bid, inner = F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    for k, (length, q) in enumerate(zip(shape, grid, strict=True)):
        place = F.expr(f"((cast(i{k} as bigint) + 1) * {q} - 1) div {length}")
        low = F.expr(f"(((cast(i{k} as bigint) + 1) * {q} - 1) div {length}) * {length} div {q}")
        high = F.expr(f"((((cast(i{k} as bigint) + 1) * {q} - 1) div {length}) + 1) * {length} div {q}")
        bid = bid * q + place
        inner = inner * (high - low) + (F.col(f"i{k}") - low)
    placed = cells.select(bid.cast("int").alias("bid"), inner.alias("at"), F.col("v").cast("double").alias("v"))
    marks = cells.sparkSession.range(prod(grid)).select(F.col("id").cast("int").alias("bid"), F.lit(-1).cast("bigint").alias("at"), F.lit(0.0).alias("v"))
    cuts = [bounds(length, q) for length, q in zip(shape, grid, strict=True)]

    def pack(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bid_ = key[0].as_py()
        place = _place(bid_, grid)
        lo = [cuts[k][place[k]] for k in range(n)]
        size = [cuts[k][place[k] + 1] - lo[k] for k in range(n)]
        flat = np.zeros(prod(size))
        for batch in batches:
            at, v = batch.column("at").to_numpy(), batch.column("v").to_numpy()
            np.add.at(flat, at[at >= 0], v[at >= 0])
        yield _batch([_row(bid_, lo, flat.reshape(size))])

    return Blocked(_by_block(placed.union(marks), grid).applyInArrow(pack, SCHEMA), tuple(shape), tuple(grid))


def to_cells(t: Blocked) -> DataFrame:
    """All cells of a blocked tensor."""
    n = len(t.shape)

    def run(batches):
        for batch in batches:
            for _, lo, x in _blocks(batch):
                index = np.indices(x.shape).reshape(n, -1)
                yield pa.RecordBatch.from_arrays([*(pa.array((index[k] + lo[k]).astype(np.int32)) for k in range(n)), pa.array(x.ravel())], names=[*(f"i{k}" for k in range(n)), "v"])

    return t.df.mapInArrow(run, ", ".join(f"i{k} int" for k in range(n)) + ", v double")


def regrid(t: Blocked, grid: Grid) -> Blocked:
    """The same tensor under another grid: overlaps travel, new blocks are put together."""
    grid = tuple(grid)
    if grid == t.grid:
        return t
    cuts = [bounds(length, q) for length, q in zip(t.shape, grid, strict=True)]
    n = len(grid)

    def cut(batches):
        for batch in batches:
            for _, lo, x in _blocks(batch):
                touched = []
                for k in range(n):
                    edges, a, b = cuts[k], lo[k], lo[k] + x.shape[k]
                    touched.append([(j, max(a, edges[j]), min(b, edges[j + 1])) for j in range(grid[k]) if edges[j] < b and edges[j + 1] > a])
                rows, stack = [], [[]]
                for options in touched:
                    stack = [s + [o] for s in stack for o in options]
                for pick in stack:
                    part = x[tuple(slice(a - lo[k], b - lo[k]) for k, (_, a, b) in enumerate(pick))]
                    rows.append(_row(_number([j for j, _, _ in pick], grid), [a for _, a, _ in pick], part))
                yield _batch(rows)

    def join(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bid = key[0].as_py()
        place = _place(bid, grid)
        lo = [cuts[k][place[k]] for k in range(n)]
        out = np.zeros([cuts[k][place[k] + 1] - lo[k] for k in range(n)])
        for batch in batches:
            for _, at, x in _blocks(batch.select(["bid", "lo", "shape", "data"])):
                out[tuple(slice(a - low, a - low + s) for a, low, s in zip(at, lo, x.shape, strict=True))] = x
        yield _batch([_row(bid, lo, out)])

    return Blocked(_by_block(t.df.mapInArrow(cut, SCHEMA), grid).applyInArrow(join, SCHEMA), t.shape, grid)


def _times(x: np.ndarray, mode: int, a: np.ndarray) -> np.ndarray:
    """Product along a mode over a (left, own, right) view: no unfolding is made."""
    left, right = prod(x.shape[:mode]), prod(x.shape[mode + 1 :])
    out = np.matmul(a, x.reshape(left, x.shape[mode], right))
    return out.reshape(*x.shape[:mode], a.shape[0], *x.shape[mode + 1 :])


def ttm(t: Blocked, mode: int, a: np.ndarray) -> Blocked:
    """t times a (rows x length) along a mode, under the tensor's grid."""
    grid, q = t.grid, t.grid[mode]
    shape = (*t.shape[:mode], a.shape[0], *t.shape[mode + 1 :])
    if q > a.shape[0]:
        raise ValueError(f"{q} blocks along mode {mode} of a product with {a.shape[0]} rows")
    matrix = share(t.df.sparkSession, np.ascontiguousarray(a, float))  # freed with the lazy product that holds it
    cuts = bounds(a.shape[0], q)

    def multiply(batches):
        for batch in batches:
            rows: dict[int, dict] = {}
            for bid, lo, x in _blocks(batch):
                part = _times(x, mode, matrix.value[:, lo[mode] : lo[mode] + x.shape[mode]])
                if q == 1:
                    rows[bid] = _row(bid, [*lo[:mode], 0, *lo[mode + 1 :]], part)
                    continue
                place = _place(bid, grid)
                for j in range(q):
                    piece = part[(slice(None),) * mode + (slice(cuts[j], cuts[j + 1]),)]
                    to = _number([*place[:mode], j, *place[mode + 1 :]], grid)
                    if to in rows:  # of blocks that share a task, partial results are added before they travel
                        piece = piece + np.frombuffer(rows[to]["data"], "<f8").reshape(rows[to]["shape"])
                    rows[to] = _row(to, [*lo[:mode], cuts[j], *lo[mode + 1 :]], piece)
            if rows:
                yield _batch(list(rows.values()))

    out = t.df.mapInArrow(multiply, SCHEMA)
    if q > 1:
        out = _by_block(out, grid).applyInArrow(_add, SCHEMA)
    return Blocked(out, shape, grid)


def _add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total, lo = None, None
    for batch in batches:
        for _, lo, x in _blocks(batch.select(["bid", "lo", "shape", "data"])):
            total = x.copy() if total is None else total + x
    yield _batch([_row(key[0].as_py(), lo, total)])


def _whole_mode_grid(t: Blocked, mode: int) -> Grid:
    """A grid of as many blocks that does not cut the mode, its longest block as short as can be. Where none fits, the most blocks that do, with a warning."""
    blocks = prod(t.grid)
    most = tuple(1 if k == mode else n for k, n in enumerate(t.shape))
    for p in (d for d in range(blocks, 0, -1) if blocks % d == 0):
        fitting = enumerate_grids(p, len(most), most)
        if len(fitting):
            if p < blocks:
                warnings.warn(f"{t.shape} has no grid of {blocks} blocks that leaves mode {mode} whole; taking {p}", stacklevel=2)
            kept = np.asarray(t.grid)
            # largest block first, then what stays as it is
            best = min(fitting.tolist(), key=lambda g: (max(-(-n // q) for k, (n, q) in enumerate(zip(t.shape, g, strict=True)) if k != mode) if len(g) > 1 else 0, int((kept != g).sum()), g))
            return tuple(best)
    raise AssertionError("one block always fits")


def _add_strips(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = None
    for batch in batches:
        for blob in batch.column("data"):
            x = np.frombuffer(blob.as_buffer(), "<f8")
            total = x.copy() if total is None else np.add(total, x, out=total)
    yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([total.tobytes()], pa.binary())], names=["at", "data"])


def _sum_strips(df: DataFrame) -> dict[int, np.ndarray]:
    """Sums of (at, part, data) strips over all parts, in two steps: about the square root of the parts meet in a task, then their sums."""
    wide = max(1, round(df.sparkSession.sparkContext.defaultParallelism ** 0.5))
    first = df.groupBy("at", F.pmod("part", F.lit(wide)).alias("group")).applyInArrow(_add_strips, "at int, data binary")
    return {r["at"]: np.frombuffer(r["data"], "<f8") for r in first.groupBy("at").applyInArrow(_add_strips, "at int, data binary").collect()}


def _strips(parts: list[tuple[int, np.ndarray]]) -> pa.RecordBatch:
    part = TaskContext.get().partitionId()
    return pa.RecordBatch.from_arrays(
        [pa.array([i for i, _ in parts], pa.int32()), pa.array([part] * len(parts), pa.int32()), pa.array([np.ascontiguousarray(x).tobytes() for _, x in parts], pa.binary())], names=["at", "part", "data"]
    )


def _cuts(n: int, columns: int, size: int = 1 << 18) -> list[tuple[int, int]]:
    """Row ranges of strips of about `size` numbers."""
    step = max(1, size // max(1, columns))
    return [(i, min(n, i + step)) for i in range(0, n, step)]


def gram(t: Blocked, mode: int) -> np.ndarray:
    """Unfolding times its transpose. Each task adds up the upper half of its blocks' products, strip by strip, and sends that once."""
    n = t.shape[mode]
    if n > GRAM_LENGTH:
        raise ValueError(f"a {n} x {n} matrix on the driver; use the distributed solver")
    whole = regrid(t, _whole_mode_grid(t, mode)) if t.grid[mode] > 1 else t
    cuts = _cuts(n, n)

    def run(batches):
        total = [np.zeros((b - a, n - a)) for a, b in cuts]
        for batch in batches:
            for _, _, x in _blocks(batch):
                m = np.moveaxis(x, mode, 0).reshape(n, -1)
                for out, (a, b) in zip(total, cuts, strict=True):
                    out += m[a:b] @ m[a:].T
        yield _strips([(a, out) for out, (a, _) in zip(total, cuts, strict=True)])

    sums, out = _sum_strips(whole.df.mapInArrow(run, "at int, part int, data binary")), np.zeros((n, n))
    for a, b in cuts:
        if a in sums:
            out[a:b, a:] = sums[a].reshape(b - a, n - a)
    return np.triu(out) + np.triu(out, 1).T


def _triangle(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    r = None
    for batch in batches:
        for n, blob in zip(batch.column("n").to_pylist(), batch.column("data"), strict=True):
            x = np.frombuffer(blob.as_buffer(), "<f8").reshape(-1, n)
            r = np.linalg.qr(x if r is None else np.vstack([r, x]), "r")
    yield _triangles(r, key[0].as_py())


def _triangles(r: np.ndarray, part: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([r.shape[1]], pa.int32()), pa.array([np.ascontiguousarray(r).tobytes()], pa.binary())], names=["part", "n", "data"])


def squeeze(t: Blocked, mode: int) -> Blocked:
    """A tensor with a mode longer than its unfolding has columns, in an orthonormal basis of that unfolding's columns: the mode becomes as long as there are columns.

    Norms, the other modes' Gram matrices and the errors of all decompositions stay as they are, up to rounding; factors of the mode are in the
    new basis. Each task makes the triangular factor of its rows, and these are stacked in two steps; neither the basis nor a whole mode is
    held anywhere. A tensor without such a mode, or with over GRAM_LENGTH columns, is given back.
    """
    rest = (*t.shape[:mode], *t.shape[mode + 1 :])
    n = prod(rest)
    if t.shape[mode] <= n or n > GRAM_LENGTH:
        return t
    whole = tuple(min(t.shape[mode], prod(t.grid)) if k == mode else 1 for k in range(len(t.shape)))

    def run(batches):
        r = None
        for batch in batches:
            for _, _, x in _blocks(batch):
                m = np.moveaxis(x, mode, 0).reshape(-1, n)
                for low in range(0, len(m), 1 << 14):
                    r = np.linalg.qr(m[low : low + (1 << 14)] if r is None else np.vstack([r, m[low : low + (1 << 14)]]), "r")
        if r is not None:
            yield _triangles(r, TaskContext.get().partitionId())

    spark, schema = t.df.sparkSession, "part int, n int, data binary"
    wide = max(1, round(spark.sparkContext.defaultParallelism**0.5))
    first = regrid(t, whole).df.mapInArrow(run, schema).groupBy(F.pmod("part", F.lit(wide)).alias("group")).applyInArrow(_triangle, schema)
    found = [np.frombuffer(x["data"], "<f8").reshape(-1, n) for x in first.collect()]
    r = np.zeros((n, n))
    top = np.linalg.qr(np.vstack(found), "r")
    r[: len(top)] = top
    made = np.ascontiguousarray(np.moveaxis(r.reshape(n, *rest), 0, mode))
    one = (1,) * len(t.shape)
    return Blocked(spark.createDataFrame([_row(0, [0] * made.ndim, made)], SCHEMA), made.shape, one)


def leading_eigvecs(g: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """k leading eigenvectors and all eigenvalues, greatest first; each vector's largest entry is positive."""
    values, vectors = np.linalg.eigh((g + g.T) / 2)
    values, vectors = values[::-1], vectors[:, ::-1][:, :k]
    return fix_signs(vectors), np.maximum(values, 0)


def fix_signs(f: np.ndarray) -> np.ndarray:
    top = np.abs(f).argmax(0)
    sign = np.sign(f[top, np.arange(f.shape[1])])
    return f * np.where(sign == 0, 1, sign)


def left_svd(t: Blocked, mode: int, k: int, solver: str = "auto", iterations: int = 60, oversample: int = 8, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """k leading left singular vectors of the unfolding and their singular values.

    gram: Gram matrix and an eigenvalue decomposition on the driver (lengths up to GRAM_LENGTH).
    distributed: block subspace iteration, in which only length x k matrices travel. auto: by the mode's length.
    """
    n = t.shape[mode]
    if solver == "gram" or solver == "auto" and n <= GRAM_LENGTH:
        f, values = leading_eigvecs(gram(t, mode), k)
        return f, np.sqrt(values[:k])
    whole = regrid(t, _whole_mode_grid(t, mode)) if t.grid[mode] > 1 else t
    whole.persist()
    spark = t.df.sparkSession
    wanted, k = k, min(n, k + oversample)
    f = np.linalg.qr(np.random.default_rng(seed).normal(size=(n, k)))[0]
    values, ritz = np.zeros(k), f
    cuts = _cuts(n, k)
    for _ in range(iterations):
        now = share(spark, f)

        def run(batches, now=now):
            total = np.zeros((n, k))
            for batch in batches:
                for _, _, x in _blocks(batch):
                    m = np.moveaxis(x, mode, 0).reshape(n, -1)
                    total += m @ (m.T @ now.value)
            yield _strips([(a, total[a:b]) for a, b in cuts])

        sums, z = _sum_strips(whole.df.mapInArrow(run, "at int, part int, data binary")), np.zeros((n, k))
        now.destroy()
        for a, b in cuts:
            if a in sums:
                z[a:b] = sums[a].reshape(b - a, k)
        inner = f.T @ z
        w, u = np.linalg.eigh((inner + inner.T) / 2)
        before, values, ritz = values, w[::-1], f @ u[:, ::-1]
        f = np.linalg.qr(z)[0]
        if np.allclose(before[:wanted], values[:wanted], rtol=1e-9):
            break
    whole.unpersist()
    return fix_signs(ritz[:, :wanted]), np.sqrt(np.maximum(values[:wanted], 0))


def collect_array(t: Blocked, limit: int = 4_000_000) -> np.ndarray:
    """A small tensor (a core) on the driver; larger ones are refused."""
    if prod(t.shape) > limit:
        raise ValueError("tensor too large for the driver")
    out = np.zeros(t.shape)
    for r in t.df.collect():
        x = np.frombuffer(r["data"], "<f8").reshape(r["shape"])
        out[tuple(slice(a, a + s) for a, s in zip(r["lo"], x.shape, strict=True))] = x
    return out


def squared_error(t: Blocked, core: np.ndarray, factors: list[np.ndarray]) -> dict[str, float]:
    """Squared gap to the reconstruction, squared norm, count, least and greatest cell: each block is rebuilt where it lies."""
    parts = share(t.df.sparkSession, (core, list(factors)))

    def run(batches):
        gap = norm = 0.0
        low, high, n = np.inf, -np.inf, 0
        for batch in batches:
            for _, lo, x in _blocks(batch):
                y, f = parts.value
                for m in sorted(range(x.ndim), key=lambda m: x.shape[m] / f[m].shape[1]):
                    y = _times(y, m, f[m][lo[m] : lo[m] + x.shape[m]])
                gap += float(((x - y) ** 2).sum())
                norm += float((x**2).sum())
                low, high, n = min(low, x.min()), max(high, x.max()), n + x.size
        yield pa.RecordBatch.from_arrays([pa.array([v]) for v in (gap, norm, float(low), float(high))] + [pa.array([n])], names=["gap", "norm", "low", "high", "n"])

    row = t.df.mapInArrow(run, "gap double, norm double, low double, high double, n long").where("n > 0").agg(F.sum("gap"), F.sum("norm"), F.min("low"), F.max("high"), F.sum("n")).first()
    parts.destroy()
    return dict(zip(("gap", "norm", "low", "high", "n"), row, strict=True))


def reconstruct(spark: SparkSession, core: np.ndarray, factors: list[np.ndarray], grid: Grid) -> Blocked:
    """The tensor that a decomposition stands for, each block rebuilt in its own task from the core and its rows of the factors: nothing is shuffled."""
    shape = tuple(f.shape[0] for f in factors)
    cuts = [bounds(n, q) for n, q in zip(shape, grid, strict=True)]
    parts, n = share(spark, (core, list(factors))), prod(grid)

    def run(batches):
        for batch in batches:
            for bid in batch.column(0).to_pylist():
                place = _place(bid, grid)
                y, f = parts.value
                for m in sorted(range(y.ndim), key=lambda m: (cuts[m][place[m] + 1] - cuts[m][place[m]]) / f[m].shape[1]):
                    y = _times(y, m, f[m][cuts[m][place[m]] : cuts[m][place[m] + 1]])
                yield _batch([_row(bid, [cuts[m][place[m]] for m in range(y.ndim)], y)])

    return Blocked(spark.range(n, numPartitions=n).mapInArrow(run, SCHEMA), shape, tuple(grid))
