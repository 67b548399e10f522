"""The experiment drivers on small settings."""

import random

import numpy as np
from pyspark.sql import functions as F

from flowlens.operators import aggregate, cube, query, serve
from flowlens.plans import metrics, workload
from flowlens.plans.queries_core import movements
from flowlens.plans.queries_serving import BOX, LEVEL

from .conftest import SF


def test_step_sweep_reports_the_best_count_and_restores_settings(spark):
    held = spark.conf.get("spark.sql.shuffle.partitions")
    rows = workload.step_sweep(spark, SF, (2, 4), (10,))
    assert [r["reducers"] for r in rows] == [2, 4] and rows[0]["best_aggregation"] in (2, 4)
    assert spark.conf.get("spark.sql.shuffle.partitions") == held and spark.conf.get("spark.sql.adaptive.enabled") == "true"


def test_growth_and_load_test(spark):
    grown = workload.scale_up(spark, SF, (1, 2))
    assert grown[1]["movements"] == 2 * grown[0]["movements"]
    rows = workload.stress(spark, SF, (1, 2), (0, 1), 40, by_clock=(1,), by_spark=2)
    assert [(r["pattern"], r["seconds"]) for r in rows] == [(p, s) for p in ("population", "hotspot") for s in (1, 2)]
    assert all(r["stored"]["queries"] == 80 and r["arrays"]["p90"] >= r["arrays"]["median"] > 0 for r in rows)
    assert rows[0]["by_clock"]["queries"] == rows[2]["by_clock"]["queries"] == 40 and "by_clock" not in rows[1] and rows[3]["spark_job"]["queries"] == 2


def test_response_times_queue_at_one_server():
    got = workload.response_times(np.array([5.0, 30.0, 5.0, 5.0]), 0.04)  # one arrival every 10 ms
    assert got.tolist() == [5.0, 30.0, 25.0, 20.0]
    assert len(workload.response_times(np.zeros(0), 1)) == 0


def test_the_stored_cube_answers_like_spark(spark):
    path, nodes, edges = workload.stored_cube(spark, SF)
    mv, server = movements(spark, SF), serve.CubeServer(path, cache_bytes=20_000)
    days = aggregate.pyramid_nodes(mv, time_bin="day").withColumn("bin", F.date_format("bin", "yyyy-MM-dd")).join(nodes.select("level", "cx", "cy"), ["level", "cx", "cy"], "left_semi").persist()
    links = aggregate.pyramid_edges(mv, time_bin="day").withColumn("bin", F.date_format("bin", "yyyy-MM-dd")).join(edges.select("level", "sx", "sy", "tx", "ty"), ["level", "sx", "sy", "tx", "ty"], "left_semi").persist()
    some = workload.asked(spark, SF, "population", (0,), 9)[0] + [(BOX, LEVEL, None), (BOX, LEVEL, ("2024-01-02", "2024-01-25")), ((0, 0, 399_360_000, 276_480_000), 1, None)]
    for box, level, period in some:
        n = query.viewport_nodes(days, box, level, period or ("0", "9"))
        e = query.viewport_edges(links, n, level, period=period or ("0", "9"))
        got = server.viewport(box, level, period)
        assert sorted(map(tuple, got[0].tolist())) == sorted((r["cx"], r["cy"], r["n"]) for r in n.collect())
        assert sorted(map(tuple, got[1].tolist())) == sorted((r["sx"], r["sy"], r["tx"], r["ty"], r["n"]) for r in e.collect())
    assert len(server.held) == 1 or server.bytes <= 20_000
    days.unpersist(), links.unpersist()


def test_morton_ranges_cover_a_box_and_little_else():
    rng = random.Random(1)
    key = lambda x, y: sum(((x >> i) & 1) << 2 * i | ((y >> i) & 1) << 2 * i + 1 for i in range(14))
    for _ in range(30):
        x, y = rng.randrange(0, 13_000), rng.randrange(0, 9_000)
        ranges = serve.morton_ranges(x, y, x + 31, y + 17)
        keys = np.array([key(i, j) for i in range(x, x + 32) for j in range(y, y + 18)])
        at = np.searchsorted(ranges[:, 1], keys)
        assert (ranges[at, 0] <= keys).all() and len(ranges) <= 100 and (np.diff(ranges.ravel()) >= 0).all()
        assert (ranges[:, 1] - ranges[:, 0] + 1).sum() < 8 * len(keys)


def test_task_seconds(spark):
    spark.catalog.clearCache()
    t = metrics.task_seconds(spark, lambda: aggregate.pyramid_nodes(movements(spark, SF)))
    assert t["map_tasks"] and t["reduce_tasks"] and t["map_s"] > 0


def test_viewports_prune_files_and_rewrites_touch_one_bin(spark, tmp_path):
    mv, path = movements(spark, SF), str(tmp_path / "cube")
    day = lambda df: df.withColumn("bin", F.date_format("bin", "yyyy-MM-dd"))
    nodes, edges = day(aggregate.pyramid_nodes(mv, time_bin="day")), day(aggregate.pyramid_edges(mv, time_bin="day"))
    cube.write(nodes, edges, path)
    read, every = workload.pruning(cube.open_cube(spark, path).nodes, BOX, LEVEL, ("2024-01-05", "2024-01-08"))
    assert 0 < read < every / 20
    total = cube.open_cube(spark, path).nodes.agg(F.sum("n")).first()[0]
    cube.write(nodes.where("bin = '2024-01-05'"), edges.where("bin = '2024-01-05'"), path)
    assert cube.open_cube(spark, path).nodes.agg(F.sum("n")).first()[0] == total


def test_bucketed_edges_join_without_a_shuffle(spark):
    spark.catalog.clearCache()
    edges = aggregate.pyramid_edges(movements(spark, SF))
    cube.save_bucketed(edges, "bucketed_edges", 4)
    try:
        t = spark.table("bucketed_edges")
        per = t.groupBy("level", "sx", "sy").count()
        plan = per._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and per.count() > 0
    finally:
        spark.sql("DROP TABLE bucketed_edges")
