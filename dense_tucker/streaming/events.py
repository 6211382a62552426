"""Streams over files of events: windows as time modes, watermarks, joins, state and incremental tensors."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.meta import TensorMeta
from ..operators import blocks as B
from ..operators import decompose as D
from ..plans.planner import Plan
from ..sources import builders as S
from ..sources.files import new_path

SLICES = 5


#: Rows of a staged file, about.
FILE_ROWS = 500_000


def stage(spark: SparkSession, sf_dir: str, late_share: int = 0) -> str:
    """Events as files in order of time (six days a slice); one of `late_share` rows comes one slice late. Every slice has as many files as the others."""
    path = new_path(spark, "events")
    e = S.read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    slot = F.greatest(F.lit(0), F.least(F.lit(SLICES - 1), F.floor(F.datediff("ts", F.lit("2024-01-01")) / 6)))
    if late_share:
        slot = F.least(F.lit(SLICES - 1), slot + (F.col("event_id") % late_share == 0).cast("int"))
    e = e.withColumn("slot", slot).persist()
    most = e.groupBy("slot").count().agg(F.max("count")).first()[0] or 0
    each = max(1, -(-most // FILE_ROWS))
    for i in range(SLICES):
        e.where(F.col("slot") == i).drop("slot").repartition(each).write.mode("append").parquet(path)
        while len(spark.read.parquet(path).inputFiles()) < each * (i + 1):  # parts without a row are not written
            spark.createDataFrame([], e.drop("slot").schema).coalesce(1).write.mode("append").parquet(path)
    e.unpersist()
    return path


def files_of_slice(spark: SparkSession, path: str) -> int:
    """How many files of a staged folder make a slice."""
    return max(1, len(spark.read.parquet(path).inputFiles()) // SLICES)


def read(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files).parquet(path)


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run over everything there is into files and give their table: all rows (append), all updates (update) or the last batch's (complete)."""
    spark, path = df.sparkSession, new_path(df.sparkSession, "drained")
    if mode == "append":
        query = df.writeStream.format("parquet").option("path", path).outputMode(mode).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(df.schema).parquet(path)
    last: list[str] = []

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")  # a replayed batch replaces itself
        last.append(f"{path}/batch={number}")

    drain_batches(df, each, mode)
    if not last:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*(last[-1:] if mode == "complete" else dict.fromkeys(last)))


def drain_to_memory(df: DataFrame) -> DataFrame:
    """The memory sink's table: all rows are held by the driver, so for small answers only."""
    spark, name = df.sparkSession, "s" + uuid.uuid4().hex
    query = df.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def drain_batches(df: DataFrame, each: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    spark = df.sparkSession
    query = df.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()


def fibers_by_user(stream: DataFrame) -> DataFrame:
    """Running 24-hour count fiber of every user, as state."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        fiber = list(state.get[0]) if state.exists else [0] * 24
        for frame in frames:
            for h, n in frame["hour"].value_counts().items():
                fiber[int(h)] += int(n)
        state.update((fiber,))
        yield pd.DataFrame({"user_id": [key[0]], "fiber": [fiber], "total": [sum(fiber)]})

    hours = stream.select("user_id", F.hour("ts").alias("hour"))
    return hours.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, fiber array<bigint>, total bigint", "fiber array<bigint>", "update", "NoTimeout")


def incremental_cells(stream: DataFrame) -> DataFrame:
    """Cells of user group x type x day x hour, as the sum of the micro-batches' deltas (tensors are linear)."""
    spark, path = stream.sparkSession, new_path(stream.sparkSession, "deltas")
    spec = S.specs()["td4"]

    def each(batch: DataFrame, number: int) -> None:
        picked = batch.select(*[F.expr(e).cast("int").alias(f"i{k}") for k, e in enumerate(spec.modes)])
        picked.groupBy("i0", "i1", "i2", "i3").agg(F.count("*").cast("double").alias("v")).write.mode("overwrite").parquet(f"{path}/batch={number}")  # a replayed batch replaces itself

    drain_batches(stream, each)
    return spark.read.parquet(path).groupBy("i0", "i1", "i2", "i3").agg(F.sum("v").alias("v"))


def warm_sweeps(stream: DataFrame, meta: TensorMeta, plan: Plan) -> list[tuple[int, float]]:
    """After every micro-batch one sweep from the last factors under the same plan: (batch, error)."""
    spark, path = stream.sparkSession, new_path(stream.sparkSession, "deltas")
    spec = S.specs()["td"]
    state: dict = {"dec": None, "errors": []}

    def each(batch: DataFrame, number: int) -> None:
        picked = batch.select(*[F.expr(e).cast("int").alias(f"i{k}") for k, e in enumerate(spec.modes)])
        picked.groupBy("i0", "i1", "i2").agg(F.count("*").cast("double").alias("v")).write.mode("overwrite").parquet(f"{path}/batch={number}")
        cells = spark.read.parquet(path).groupBy("i0", "i1", "i2").agg(F.sum("v").alias("v"))
        t = B.distribute(cells, meta.L, plan.scheme.grids[0])
        dec = state["dec"] or D.seq_init(t, meta)
        state["dec"] = D.sweep(t, dec, plan, "latest")
        state["errors"].append((number, D.errors(t, state["dec"], "norms")["rel_error"]))

    drain_batches(stream, each)
    return state["errors"]
