"""Measures over strategies: planning at scale, normalised ratios, percentile curves, shares and dominance."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..model.meta import NoValidGrid, TensorMeta
from ..plans.planner import STRATEGIES, strategy

PLAN_SCHEMA = "tensor_id string, strategy string, load double, volume double, ttm_volume double, regrid_volume double, regrids int, ttms int, cells double, relative_volume double, planner_s double"


def plan_all(metas: DataFrame, names: tuple[str, ...] = tuple(STRATEGIES), partitions: int = 16) -> DataFrame:
    """One row for each tensor and strategy; planning runs beside the data, a batch of metas in each task."""

    def run(frames):
        from ..plans.trees import ttm_count

        for frame in frames:
            rows = []
            for r in frame.itertuples():
                meta = TensorMeta(tuple(r.L), tuple(r.K), r.tensor_id)
                for name in names:
                    try:
                        p = strategy(meta, int(r.p), name)
                    except NoValidGrid:
                        continue
                    rows.append((r.tensor_id, name, float(p.load), float(p.volume), float(p.scheme.ttm), float(p.scheme.regrid), p.scheme.regrids, ttm_count(p.tree), float(meta.cardinality()), p.relative_volume, p.stats["planner_s"]))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in PLAN_SCHEMA.split(", ")])

    return metas.repartition(partitions, "tensor_id").mapInPandas(run, PLAN_SCHEMA)


def normalise(df: DataFrame, metric: str, ref: str = "opt_dynamic", key: str = "tensor_id") -> DataFrame:
    """Adds <metric>_ratio: the metric over the reference strategy's, within each tensor."""
    base = df.where(F.col("strategy") == ref).select(key, F.col(metric).alias("__ref"))
    ratio = F.when((F.col("__ref") == 0) & (F.col(metric) == 0), 1.0).otherwise(F.try_divide(F.col(metric), F.col("__ref")))
    return df.join(base, key).withColumn(f"{metric}_ratio", ratio).drop("__ref")


def percentile_curve(df: DataFrame, value: str, ks: list[int], by: str = "strategy") -> DataFrame:
    """by, k and t: k per cent of tensors have a value up to t."""
    p = F.percentile(value, F.array(*[F.lit(k / 100) for k in ks]))
    return df.groupBy(by).agg(p.alias("ts")).select(by, F.posexplode("ts").alias("at", "t")).select(by, F.element_at(F.array(*map(F.lit, ks)), F.col("at") + 1).alias("k"), "t")


def extreme_gains(df: DataFrame, value: str, key: str = "tensor_id", by: str = "strategy") -> DataFrame:
    return df.groupBy(by).agg(F.min_by(key, value).alias("least_tensor"), F.min(value).alias("least"), F.max_by(key, value).alias("greatest_tensor"), F.max(value).alias("greatest"), F.median(value).alias("median"))


def gain_share(df: DataFrame, value: str, least: float, by: str = "strategy") -> DataFrame:
    return df.groupBy(by).agg(F.avg((F.col(value) >= least).cast("int")).alias("share"))


def dominates(df: DataFrame, value: str, by: str = "strategy") -> DataFrame:
    """Is the reference nowhere beaten?"""
    return df.groupBy(by).agg(F.bool_and(F.col(value) >= 1 - 1e-12).alias("dominated"))


def rank_share(value: str, by: str) -> Column:
    return F.cume_dist().over(Window.partitionBy(by).orderBy(value))
