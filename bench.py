"""Headline timings and the published experiments: one JSON line. BENCH_SF_DIR and BENCH_CPUS choose data and cores; BENCH_FULL=1 runs
the step sweep over all partition counts with means of three, growth by three as well, and every rate of the stress test by the clock."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from flowlens.config import PyramidConfig
from flowlens.operators import aggregate, bloom, summarize
from flowlens.plans import metrics, queries_serving, workload
from flowlens.registry import QUERIES

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
HEADLINE = [
    "movements_from_events", "pyramid_nodes", "pyramid_nodes_rollup", "pyramid_edges", "pyramid_edges_rollup", "significant_nodes_tiles", "significant_nodes_offsets",
    "edges_bloom", "edges_join", "final_graph", "final_graph_bloom", "viewport_batch_all", "viewport_raw", "cube_nodes_daily", "load_stats_16",
]
FULL = bool(os.environ.get("BENCH_FULL"))


def seconds(make) -> float:
    t = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def main() -> None:
    spark = (SparkSession.builder.master(f"local[{CPUS}]").appName("flowlens-bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
             .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    times = {}
    for name in HEADLINE:
        runs = []
        for _ in range(2):
            spark.catalog.clearCache()
            runs.append(seconds(lambda name=name: QUERIES[name](spark, SF_DIR)))
        times[name] = round(min(runs), 3)
    # the three steps over movements that are at hand, as the published step times have them
    cfg = PyramidConfig()
    mv = queries_serving.movements(spark, SF_DIR).persist()
    n = mv.count()
    steps = {}
    for _ in range(2):
        spark.catalog.clearCache()
        mv = queries_serving.movements(spark, SF_DIR).persist()
        mv.count()
        t0 = time.perf_counter()
        nodes, edges = aggregate.pyramid_nodes(mv, cfg).persist(), aggregate.pyramid_edges(mv, cfg).persist()
        nodes.count(), edges.count()
        t1 = time.perf_counter()
        kept = summarize.significant_nodes(nodes, cfg).persist()
        kept.count()
        t2 = time.perf_counter()
        seconds(lambda: bloom.bloom_filter_edges(edges, kept))
        t3 = time.perf_counter()
        steps = {"aggregation": round(t1 - t0, 3), "summarization": round(t2 - t1, 3), "filtering": round(t3 - t2, 3)}
    overall = sum(steps.values())
    out = {"metric": "three_step_overall", "value": round(overall, 3), "unit": "sec", "queries": times | {f"step_{k}": v for k, v in steps.items()},
           "sf": SF_DIR.rsplit("/sf", 1)[-1], "movements": n, "movements_per_s": round(n / overall), "movements_per_s_core": round(n / overall / int(CPUS))}
    spark.catalog.clearCache()
    out["scale"] = workload.scale_up(spark, SF_DIR, (1, 3, 10) if FULL else (1, 10))
    out["scaled_movements_per_s_core"] = round(out["scale"][-1]["movements"] / out["scale"][-1]["overall"] / int(CPUS))
    out["reducer_load"] = [r.asDict() for r in QUERIES["load_stats_methods"](spark, SF_DIR).collect()]
    out["graph_size"] = workload.graph_sizes(spark, SF_DIR)
    out["step_times"] = workload.step_sweep(spark, SF_DIR, runs=3) if FULL else workload.step_sweep(spark, SF_DIR, (4, 16, 64))
    out["ablations"] = workload.ablations(spark, SF_DIR, times=10)
    spark.catalog.clearCache()
    out["task_seconds"] = metrics.task_seconds(spark, lambda: aggregate.pyramid_nodes(queries_serving.movements(spark, SF_DIR), cfg))
    # every query runs; the clock itself only at the highest rate, unless all is asked for
    out["stress_ms"] = workload.stress(spark, SF_DIR, by_clock=workload.DURATIONS if FULL else (50,), by_spark=10)
    print(json.dumps(out))


if __name__ == "__main__":
    main()
