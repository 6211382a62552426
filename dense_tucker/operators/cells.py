"""Relational tensor algebra on cells (i0.., v): exact on integers, checkable by SQL, for small or sparse work."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


#: Longest mode of a relational Gram matrix.
RELATIONAL_LENGTH = 512


def keys(cells: DataFrame) -> list[str]:
    return [c for c in cells.columns if c != "v"]


def matrix_frame(spark: SparkSession, a: np.ndarray) -> DataFrame:
    """k, l, a rows of a small dense matrix; sizes above 4 million entries are refused."""
    if a.size > 4_000_000:
        raise ValueError("matrix too large for the relational form; use blocks")
    k, col = np.indices(a.shape)
    import pandas as pd

    return spark.createDataFrame(pd.DataFrame({"k": k.ravel().astype("int32"), "l": col.ravel().astype("int32"), "a": a.ravel().astype(float)}))


def integer_matrix(spark: SparkSession, k: int, n: int) -> DataFrame:
    """Fixed integer matrix of the tests: entries -2..2 by a rule of the indices."""
    grid = spark.range(k * n).select((F.col("id") / n).cast("int").alias("k"), (F.col("id") % n).cast("int").alias("l"))
    return grid.withColumn("a", (((F.col("l") + 1) * (F.col("k") + 2)) % 5 - 2).cast("double"))


def ttm(cells: DataFrame, mode: int, matrix: DataFrame) -> DataFrame:
    """Multiply along a mode: broadcast the small matrix (bounded by matrix_frame), sum with partial aggregation."""
    own = f"i{mode}"
    rest = [c for c in keys(cells) if c != own]
    joined = cells.join(F.broadcast(matrix), cells[own] == matrix["l"])
    out = joined.groupBy(*rest, F.col("k").alias(own)).agg(F.sum(F.col("v") * F.col("a")).alias("v"))
    return out.select(*keys(cells), "v")


def best_order(shapes: dict[int, tuple[int, int]]) -> list[int]:
    """Order of least flops for a chain of (rows x length) matrices.

    Of two neighbours a, b the cost of a first is K_a + K_b K_a / L_a, so a goes first where K_a / (1 - K_a / L_a) is less; where a matrix does not
    shrink its mode it goes last, those that grow least first.
    """

    def rank(m: int) -> tuple[int, float, int]:
        rows, length = shapes[m]
        return (0, rows / (1 - rows / length), m) if rows < length else (1, rows / max(rows / length - 1, 1e-12) * -1, m)

    return sorted(shapes, key=rank)


def ttm_chain(cells: DataFrame, matrices: dict[int, DataFrame], order: list[int] | str | None = None, shapes: dict[int, tuple[int, int]] | None = None) -> DataFrame:
    """Products along several modes, in any order; "best" takes the cheapest one by the matrices' (rows, length)."""
    if order == "best":
        order = best_order(shapes)
    for m in order or sorted(matrices):
        cells = ttm(cells, m, matrices[m])
    return cells


def to_fibers(cells: DataFrame, mode: int) -> DataFrame:
    """Other coordinates and x: the values along a mode in order of the index."""
    own = f"i{mode}"
    rest = [c for c in keys(cells) if c != own]
    packed = cells.groupBy(*rest).agg(F.array_sort(F.collect_list(F.struct(own, "v"))).alias("x"))
    return packed.select(*rest, F.transform("x", lambda s: s["v"]).alias("x"))


def ttm_fibers(fibers: DataFrame, mode: int, a: np.ndarray) -> DataFrame:
    """Multiply whole fibers without any exchange; rows of `a` are literals."""
    own = f"i{mode}"
    rest = [c for c in fibers.columns if c != "x"]

    def dot(row: np.ndarray) -> Column:
        weights = F.array(*[F.lit(float(w)) for w in row])
        return F.aggregate(F.zip_with("x", weights, lambda p, q: p * q), F.lit(0.0), lambda s, p: s + p)

    out = fibers.select(*rest, F.posexplode(F.array(*[dot(r) for r in a])).alias(own, "v"))
    return out.select(*sorted([*rest, own], key=lambda c: int(c[1:])), "v")


def unfold(cells: DataFrame, mode: int, L: tuple[int, ...]) -> DataFrame:
    """row (index along the mode), col (lexicographic number of the other coordinates) and v."""
    col: Column = F.lit(0).cast("bigint")
    for k, n in enumerate(L):
        if k != mode:
            col = col * n + F.col(f"i{k}")
    return cells.select(F.col(f"i{mode}").alias("row"), col.alias("col"), "v")


def fold(matrix: DataFrame, mode: int, L: tuple[int, ...]) -> DataFrame:
    """Inverse of unfold."""
    columns: dict[int, Column] = {mode: F.col("row").cast("int")}
    step = 1
    for k in reversed([k for k in range(len(L)) if k != mode]):
        columns[k] = F.expr(f"cast((col div {step}) % {L[k]} as int)")
        step *= L[k]
    return matrix.select(*[columns[k].alias(f"i{k}") for k in range(len(L))], "v")


def gram(cells: DataFrame, mode: int, L: tuple[int, ...]) -> DataFrame:
    """i, j, g with i <= j: inner products of the unfolding's rows, by a self join on the column.

    A column makes length^2 / 2 rows, so modes longer than RELATIONAL_LENGTH are refused; blocks have no such limit.
    """
    if L[mode] > RELATIONAL_LENGTH:
        raise ValueError(f"mode of length {L[mode]}: use blocks")
    m = unfold(cells, mode, L)
    a, b = m.selectExpr("row as i", "col", "v as x"), m.selectExpr("row as j", "col", "v as y")
    return a.join(b, "col").where("i <= j").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g"))


def reconstruct(core: DataFrame, factors: list[np.ndarray]) -> DataFrame:
    """Expand the core along all modes, those that grow least first."""
    spark = core.sparkSession
    order = sorted(range(len(factors)), key=lambda m: factors[m].shape[0] / factors[m].shape[1])
    return ttm_chain(core, {m: matrix_frame(spark, f) for m, f in enumerate(factors)}, order)


def reconstruct_slice(core: DataFrame, factors: list[np.ndarray], ranges: dict[int, tuple[int, int]]) -> DataFrame:
    """Cells within half-open index ranges of some modes, without expanding the rest of those modes."""
    cut = [f[slice(*ranges.get(m, (0, f.shape[0])))] for m, f in enumerate(factors)]
    out = reconstruct(core, cut)
    return out.select(*[(F.col(f"i{m}") + ranges.get(m, (0, 0))[0]).cast("int").alias(f"i{m}") for m in range(len(factors))], "v")


def norms(cells: DataFrame) -> DataFrame:
    return cells.agg(F.sum(F.col("v") * F.col("v")).alias("norm2"), F.max(F.abs("v")).alias("max_abs"), F.sum(F.abs("v")).alias("l1"))


def compare(one: DataFrame, two: DataFrame) -> DataFrame:
    """Error measures of a second tensor against the first, in one pass over the joined cells."""
    joined = one.withColumnRenamed("v", "x").join(two.withColumnRenamed("v", "y"), keys(one), "full").fillna(0.0, ["x", "y"])
    gap = (F.col("x") - F.col("y")) ** 2
    return joined.agg(
        F.sqrt(F.sum(gap) / F.sum(F.col("x") ** 2)).alias("rel_error"),
        F.sqrt(F.avg(gap)).alias("rmse"),
        (F.sqrt(F.avg(gap)) / (F.max("x") - F.min("x"))).alias("nrmse_range"),
    )


def as_array(cells: DataFrame, L: tuple[int, ...], limit: int = 4_000_000) -> np.ndarray:
    """Small tensor on the driver (tests, cores); larger ones are refused."""
    if int(np.prod(L)) > limit:
        raise ValueError("tensor too large for the driver")
    out = np.zeros(L)
    pdf = cells.toPandas()
    out[tuple(pdf[c].to_numpy() for c in keys(cells))] = pdf["v"].to_numpy()
    return out


def from_array(spark: SparkSession, a: np.ndarray) -> DataFrame:
    import pandas as pd

    index = np.indices(a.shape).reshape(a.ndim, -1)
    return spark.createDataFrame(pd.DataFrame({f"i{k}": index[k].astype("int32") for k in range(a.ndim)} | {"v": a.ravel().astype(float)}))


