"""What Spark's own status store says about the stages that a block of code ran."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import SparkSession

_GROUP = ("spark.jobGroup.id", "spark.job.description")


@dataclass
class StageTotals:
    """Sums over tasks: bytes written to and read from shuffles; seconds of tasks and of their shuffle writes and fetch waits."""

    stages: int = 0
    shuffle_bytes: int = 0
    read_bytes: int = 0
    task_s: float = 0.0
    shuffle_s: float = 0.0

    def __iadd__(self, other: StageTotals) -> StageTotals:
        for name, value in vars(other).items():
            setattr(self, name, getattr(self, name) + value)
        return self


@contextmanager
def observed(spark: SparkSession) -> Iterator[StageTotals]:
    """Fills the totals when the block ends. Only jobs of this thread count; skipped stages and those no longer retained add nothing."""
    sc = spark.sparkContext
    before = [sc.getLocalProperty(k) for k in _GROUP]
    group, seen = f"observed-{uuid.uuid4().hex}", StageTotals()
    sc.setJobGroup(group, "observed")
    try:
        yield seen
    finally:
        for key, value in zip(_GROUP, before, strict=True):
            sc.setLocalProperty(key, value)
    core, tracker = sc._jsc.sc(), sc.statusTracker()
    core.listenerBus().waitUntilEmpty()  # the store is filled by a listener
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    stages = {s for j in jobs if j is not None for s in j.stageIds}
    store, no_tasks, no_quantiles = core.statusStore(), sc._jvm.java.util.ArrayList(), sc._gateway.new_array(sc._jvm.double, 0)
    for number in sorted(stages):
        attempts = store.stageData(number, False, no_tasks, False, no_quantiles)
        for data in (attempts.apply(i) for i in range(attempts.size())):
            if data.numCompleteTasks():
                seen += StageTotals(1, data.shuffleWriteBytes(), data.shuffleReadBytes(), data.executorRunTime() / 1e3, data.shuffleWriteTime() / 1e9 + data.shuffleFetchWaitTime() / 1e3)
