"""Planner functions, table functions and a random-tensor data source for SQL."""

from __future__ import annotations

from collections.abc import Iterator
from math import prod

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model.meta import TensorMeta
from ..plans import grids as G
from ..plans.planner import STRATEGIES, strategy


@F.pandas_udf(T.DoubleType())
def block_sum(data: pd.Series) -> pd.Series:
    """Sum of a packed block's elements."""
    return data.map(lambda x: float(np.frombuffer(x, "<f8").sum()))


def _plan(L, K, p, name):
    if name not in STRATEGIES:
        raise ValueError(f"unknown strategy {name}")
    return strategy(TensorMeta(tuple(L), tuple(K)), int(p), name)


def tucker_load(L, K, name):
    return float(_plan(L, K, 1, name).load)


def tucker_volume(L, K, p, name):
    return float(_plan(L, K, p, name).volume)


def grid_count(p, n):
    return G.count_grids(int(p), int(n))


@F.udtf(returnType=T.StructType([T.StructField("grid", T.StringType())]))
class Grids:
    """All grids of p blocks over n modes."""

    def eval(self, p: int, n: int):
        for g in G.enumerate_grids(p, n):
            yield ("x".join(str(int(x)) for x in g),)


_PLAN = [("node", T.IntegerType()), ("parent", T.IntegerType()), ("kind", T.StringType()), ("mode", T.IntegerType()), ("grid", T.ArrayType(T.IntegerType())), ("flop", T.DoubleType())]


@F.udtf(returnType=T.StructType([T.StructField(n, t) for n, t in _PLAN]))
class PlanRows:
    """Nodes of a plan."""

    def eval(self, L: list, K: list, p: int, name: str):
        for r in _plan(L, K, p, name).rows():
            yield r["node"], r["parent"], r["kind"], r["mode"], [int(x) for x in r["grid"]], float(r["flop"])


class _Part(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _RandomReader(DataSourceReader):
    def __init__(self, options):
        self.L = [int(x) for x in options["lengths"].split(",")]
        self.n = int(options.get("partitions", "4"))

    def partitions(self):
        total = prod(self.L)
        return [_Part(i * total // self.n, (i + 1) * total // self.n) for i in range(self.n)]

    def read(self, part: _Part) -> Iterator[tuple]:
        for at in range(part.low, part.high):
            rest, place = at, []
            for n in reversed(self.L):
                place.append(rest % n)
                rest //= n
            yield (*reversed(place), float(((at % 1000003) * 7919 + 104729) % 1009))


class RandomTensor(DataSource):
    """Cells of a deterministic pseudo-random tensor; option lengths = '6,5,4'."""

    @classmethod
    def name(cls):
        return "tensor_random"

    def schema(self):
        return ", ".join(f"i{k} int" for k in range(len(self.options["lengths"].split(",")))) + ", v double"

    def reader(self, schema):
        return _RandomReader(self.options)


def read_random(spark: SparkSession, L: tuple[int, ...]) -> DataFrame:
    spark.dataSource.register(RandomTensor)
    return spark.read.format("tensor_random").option("lengths", ",".join(map(str, L))).load()


def register(spark: SparkSession) -> None:
    """grid_count, tucker_load, tucker_volume, tucker_grids and tucker_plan."""
    spark.udf.register("grid_count", grid_count, "bigint")
    spark.udf.register("tucker_load", tucker_load, "double")
    spark.udf.register("tucker_volume", tucker_volume, "double")
    spark.udtf.register("tucker_grids", Grids)
    spark.udtf.register("tucker_plan", PlanRows)
