"""Registered queries: every method, measure and experiment over the given tables, with SQL twins where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


def all_queries() -> tuple[dict[str, Query], dict[str, str]]:
    from . import experiments, planning, relational, streams, tensors

    queries: dict[str, Query] = {}
    oracles: dict[str, str] = {}
    for module in (tensors, planning, experiments, relational, streams):
        queries |= module.QUERIES
        oracles |= module.ORACLES
    return queries, oracles
