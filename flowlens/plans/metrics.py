"""Cost and accuracy measures: partition load, sizes, reduction, replication, latency, time."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def load(df: DataFrame, by: str = "leaf") -> DataFrame:
    """records, avg_load, std_load, min_load, max_load of the rows per partition (population deviation), max and deviation over average."""
    per = df.groupBy(by).agg(F.count("*").alias("c"))
    out = per.agg(F.sum("c").alias("records"), F.avg("c").alias("avg_load"), F.stddev_pop("c").alias("std_load"), F.min("c").alias("min_load"), F.max("c").alias("max_load"))
    return out.withColumns({"max_over_avg": F.col("max_load") / F.col("avg_load"), "std_over_avg": F.col("std_load") / F.col("avg_load")})


def latency(df: DataFrame, column: str = "ms") -> DataFrame:
    return df.agg(F.count("*").alias("queries"), F.avg(column).alias("average"), F.percentile(column, 0.5).alias("median"), F.percentile(column, 0.9).alias("p90"))


def timed(make, runs: int = 3) -> float:
    """Mean seconds of so many runs into a sink that keeps nothing."""
    total = 0.0
    for _ in range(runs):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        total += time.perf_counter() - t
    return total / runs


def edge_bound(cells: int) -> int:
    """Undirected edges without loops among so many cells."""
    return cells * (cells - 1) // 2


def task_seconds(spark, make) -> dict[str, float]:
    """Tasks and their mean run time in the stages that computing a frame runs, by whether they write a shuffle (map side) or not."""
    store = spark.sparkContext._jsc.sc().statusStore()
    ids = lambda: {s.stageId() for s in _stages(store)}
    before = ids()
    make().write.format("noop").mode("overwrite").save()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    out: dict = {}
    for _ in range(20):  # the store follows the listeners with a delay
        out = {"map_tasks": 0, "map_s": 0.0, "reduce_tasks": 0, "reduce_s": 0.0}
        for s in _stages(store):
            if s.stageId() not in before and s.numCompleteTasks():
                side = "map" if s.shuffleWriteRecords() else "reduce"
                out[f"{side}_tasks"] += s.numCompleteTasks()
                out[f"{side}_s"] += s.executorRunTime() / 1000
        if out["reduce_tasks"]:
            break
        time.sleep(0.2)
    for side in ("map", "reduce"):
        out[f"{side}_s"] = round(out[f"{side}_s"] / max(1, out[f"{side}_tasks"]), 4)
    return out


def _stages(store) -> list:
    listed = store.stageList(None, False, False, _no_quantiles(), None)
    return [listed.apply(i) for i in range(listed.size())]


def _no_quantiles():
    from pyspark import SparkContext

    return SparkContext._gateway.new_array(SparkContext._jvm.double, 0)
