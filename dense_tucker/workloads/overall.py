"""Overall times over more inputs of the benchmark than a registered query runs: `python -m dense_tucker.workloads.overall [inputs] [cores]`."""

from __future__ import annotations

import sys

from pyspark.sql import SparkSession

from . import experiments as X


def main(count: int = 20, cores: int = 8) -> None:
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(cores)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    X.overall_sweeps(spark, X.shrunk(5, 1), 32)  # start workers and compile
    for n in (5, 6):
        made = []
        for meta in X.shrunk(n, count):
            made += X.overall_sweeps(spark, [meta], 32)
            print(meta.name, meta.L, meta.K, *(f"{r[1]} {r[4]:.1f}" for r in made[-5:]), flush=True)
        rows = spark.createDataFrame(made, X._OVERALL).persist()
        print(n, "modes,", count, "inputs")
        X.overall_curve(rows).orderBy("strategy", "k").show(100, False)
        rows.groupBy("strategy").agg({"wall_s": "avg", "compute_task_s": "avg", "comm_task_s": "avg", "shuffle_bytes": "avg"}).show(100, False)
    spark.stop()


if __name__ == "__main__":
    main(*map(int, sys.argv[1:]))
