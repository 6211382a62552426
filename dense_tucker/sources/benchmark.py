"""Metadata benchmarks: all tensors whose lengths and shrink ratios come from fixed sets, under a size limit."""

from __future__ import annotations

from itertools import combinations_with_replacement, product
from math import prod

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.meta import TensorMeta

#: Fixed sets of the experiments. The ratios are L/K; all quotients are whole.
LENGTHS = (20, 50, 100, 400)
RATIOS = (1.25, 2.0, 5.0, 10.0)
LIMIT = 8 * 10**9
#: Published numbers of inputs; which ones is not derivable, so a hash sample of ours has this size.
PUBLISHED = {5: 1134, 6: 642}


def enumerate_metas(n: int, rule: str = "pairs", limit: int = LIMIT) -> list[TensorMeta]:
    """pairs: multisets of (length, ratio); lengths: multisets of lengths with multisets of ratios; tuples: ordered lengths, ratio 2."""
    if rule == "pairs":
        options = list(product(LENGTHS, RATIOS))
        rows = combinations_with_replacement(options, n)
    elif rule == "lengths":
        rows = (tuple(zip(a, b, strict=True)) for a in combinations_with_replacement(LENGTHS, n) for b in combinations_with_replacement(RATIOS, n))
    elif rule == "tuples":
        rows = (tuple((x, 2.0) for x in a) for a in product(LENGTHS, repeat=n))
    else:
        raise ValueError(rule)
    out = []
    for row in rows:
        L = tuple(x for x, _ in row)
        if prod(L) <= limit:
            out.append(TensorMeta(L, tuple(round(x / r) for x, r in row)))
    return out


def meta_frame(spark: SparkSession, metas: list[TensorMeta], p: int = 32) -> DataFrame:
    """tensor_id, n, L, K, p."""
    rows = [(m.name or "x".join(map(str, m.L)) + "->" + "x".join(map(str, m.K)), m.n, list(m.L), list(m.K), p) for m in metas]
    return spark.createDataFrame(rows, "tensor_id string, n int, L array<bigint>, K array<bigint>, p int")


def sample(df: DataFrame, n: int) -> DataFrame:
    """A fixed hash sample of the published size."""
    return df.orderBy(F.md5("tensor_id")).limit(n)


def benchmark(spark: SparkSession, n: int, p: int = 32) -> DataFrame:
    return sample(meta_frame(spark, enumerate_metas(n), p), PUBLISHED[n])
