"""Worked examples, invariants and special cases."""

import datetime as dt
import random
import warnings
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from flowlens.config import GridSpec, PyramidConfig
from flowlens.functions import geo, grid
from flowlens.operators import aggregate, bloom, bundling, partitioning, query, summarize, trajectory
from flowlens.plans import metrics, workload
from flowlens.plans.queries_core import movements
from flowlens.plans.queries_serving import views
from flowlens.registry import QUERIES
from flowlens.sources import carriers, sql, tables

from .conftest import SF

CFG = PyramidConfig()
POINTS = "point_id long, user_id long, ts timestamp_ntz, x_mas long, y_mas long"


def at(s):
    return dt.datetime(2024, 1, 1) + dt.timedelta(seconds=s)


def points(spark, rows):
    return spark.createDataFrame([(i, u, at(s), x, y) for i, (u, s, x, y) in enumerate(rows)], POINTS)


def node_frame(spark, rows):
    return spark.createDataFrame(rows, "level int, cx long, cy long, n long")


def cells(df):
    return sorted(tuple(r) for r in df.select("level", "cx", "cy").collect())


def test_coarsest_grid_and_edge_bound():
    assert CFG.grid.shape(10) == (26, 18) and metrics.edge_bound(468) == 109_278
    assert [CFG.grid.nominal_km(i) for i in range(1, 11)] == [1 << i for i in range(10)]


def test_movement_inside_a_cell_counts_twice_and_loops(spark):
    mv = trajectory.build_movements(points(spark, [(1, 0, 100, 100), (1, 60, 200, 200), (1, 120, 300, 300)]))
    for how in ("rollup", "explode", "in_task", "builtin", "none"):
        n = {r["level"]: r["n"] for r in aggregate.pyramid_nodes(mv, CFG, how).collect()}
        assert n == {i: 4 for i in range(1, 11)}, how
    e = aggregate.pyramid_edges(mv, CFG).where("level = 1").collect()
    assert [(r["sx"], r["tx"], r["n"]) for r in e] == [(0, 0, 2)]


def test_one_point_and_empty_input(spark):
    assert trajectory.build_movements(points(spark, [(1, 0, 5, 5)])).count() == 0
    none = trajectory.build_movements(points(spark, []))
    nodes = aggregate.pyramid_nodes(none, CFG)
    assert nodes.count() == 0 and summarize.significant_nodes(nodes, CFG).count() == 0
    assert bloom.bloom_filter_edges(aggregate.pyramid_edges(none, CFG), nodes).count() == 0


def test_meridian_degree(spark):
    km = spark.range(1).select(geo.great_circle_km(F.lit(0), F.lit(0), F.lit(0), F.lit(3_600_000))).first()[0]
    assert abs(km - 111.195) < 0.001


def test_rank_forms(spark):
    nodes = node_frame(spark, [(1, 5, 5, 2), (1, 5, 6, 1), (1, 6, 5, 2), (1, 6, 6, 5)])
    r = summarize.node_scores(nodes, CFG).where("cx = 5 and cy = 5").first()
    assert (r["rank_weak"], r["rank_strict"], r["rank_mean"]) == (0.75, 0.25, 0.5) and abs(r["rank_relative"] - 1 / 3) < 1e-12
    alone = node_frame(spark, [(1, 100, 100, 1)])
    assert summarize.significant_nodes(alone, CFG).count() == 1
    assert summarize.significant_nodes(alone, replace(CFG, rank="strict")).count() == 0


def test_bloom_size_and_limits():
    assert bloom.size(1000, 0.01) == (9586, 7) and bloom.size(0) == (1, 1)
    m, k = bloom.tune(1000, max_bytes=100)
    assert m == 800 and k == 1


def test_invariants(spark):
    mv = movements(spark, SF).persist()
    n = mv.count()
    nodes, edges = aggregate.pyramid_nodes(mv, CFG), aggregate.pyramid_edges(mv, CFG)
    assert {r["level"]: r["s"] for r in nodes.groupBy("level").agg(F.sum("n").alias("s")).collect()} == {i: 2 * n for i in range(1, 11)}
    d = [r[0] for r in mv.select("dist_km").collect()]
    got = {r["level"]: r["s"] for r in edges.groupBy("level").agg(F.sum("n").alias("s")).collect()}
    assert got == {i + 1: sum(x < c for x in d) for i, c in enumerate(CFG.caps)}
    up = nodes.where("level = 3").groupBy(grid.parent(F.col("cx")).alias("cx"), grid.parent(F.col("cy")).alias("cy")).agg(F.sum("n").alias("n"))
    assert up.exceptAll(nodes.where("level = 4").select("cx", "cy", "n")).count() == 0
    c = aggregate.centroids(nodes)
    inside = (grid.cell(F.col("cent_x"), F.col("level")) == F.col("cx")) & (grid.cell(F.col("cent_y"), F.col("level")) == F.col("cy"))
    assert c.where(~inside).count() == 0


def test_summary_is_the_same_for_every_strategy_and_partition_count(spark):
    rng = random.Random(3)
    made = {(1 + rng.randrange(3), rng.randrange(40), rng.randrange(30)): rng.randrange(1, 9) for _ in range(900)}
    nodes = node_frame(spark, [(*k, v) for k, v in made.items()])
    for metric in ("grid_circle", "grid_box"):
        cfg = replace(CFG, metric=metric)
        want = cells(summarize.significant_nodes(nodes, cfg, "all_pairs"))
        assert cells(summarize.significant_nodes(nodes, cfg, "tiles")) == want == cells(summarize.significant_nodes(nodes, cfg, "offsets"))
        at_ = nodes.select(grid.centre(F.col("cx"), F.col("level")).alias("x"), grid.centre(F.col("cy"), F.col("level")).alias("y"))
        for k in (1, 2, 6, 16):
            assert cells(summarize.significant_nodes(nodes, cfg, "leaves", partitioning.learn(at_, k))) == want, (metric, k)
    geo_ = replace(CFG, metric="great_circle")
    assert cells(summarize.significant_nodes(nodes, geo_, "tiles")) == cells(summarize.significant_nodes(nodes, geo_, "all_pairs")) == cells(summarize.significant_nodes(nodes, geo_, "offsets"))


def test_bloom_loses_nothing(spark):
    mv = movements(spark, SF)
    nodes, edges = aggregate.pyramid_nodes(mv, CFG).persist(), aggregate.pyramid_edges(mv, CFG).persist()
    kept = summarize.significant_nodes(nodes, CFG).persist()
    exact, passed = bloom.join_filter_edges(edges, kept), bloom.bloom_filter_edges(edges, kept, 0.1)
    assert exact.exceptAll(passed).count() == 0 and passed.exceptAll(edges.select(passed.columns)).count() == 0


@pytest.mark.parametrize("axis", ["best", "alternate", "stripes"])
def test_bisection_covers_and_balances(axis):
    p = np.random.default_rng(1).integers(0, 200_000_000, (4000, 2))
    for k in (1, 2, 6, 16):
        t = partitioning.bisect(p, k, axis=axis)
        assert len(t.leaves) == k and sum((v.x1 - v.x0) * (v.y1 - v.y0) for v in t.leaves) == 399_360_000 * 276_480_000
        load = [((p[:, 0] >= v.x0) & (p[:, 0] < v.x1) & (p[:, 1] >= v.y0) & (p[:, 1] < v.y1)).sum() for v in t.leaves]
        assert sum(load) == 4000 and (axis == "stripes" or max(load) <= 1.05 * 4000 / k + 1)


def test_bisection_of_one_position_warns():
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        t = partitioning.bisect(np.full((50, 2), 7), 8)
    assert len(t.leaves) == 1 and seen


def test_rtree_finds_what_a_scan_finds():
    p = np.random.default_rng(2).integers(0, 300_000_000, (5000, 2))
    t = partitioning.bisect(p, 37)
    levels = partitioning.packed_rtree(t.leaves)
    for x, y in p[:300].tolist():
        for r in (0, 5_000_000):
            want = sorted(v.leaf for v in t.leaves if v.x0 <= x + r and v.x1 > x - r and v.y0 <= y + r and v.y1 > y - r)
            assert partitioning.rtree_search(levels, x - r, y - r, x + r, y + r) == want


def test_work_sample_balances_like_the_published_loads(spark):
    from flowlens.plans.queries_serving import QUERIES

    r = QUERIES["load_stats_8"](spark, SF).first()
    assert r["max_over_avg"] < 1.6 and r["records"] > 0


def test_configuration_is_checked():
    for bad in ({"threshold": 1.0}, {"radius_cells": (0,) * 10}, {"caps_km": (2.0,) + (1.0,) * 9}, {"partitions": 0}):
        with pytest.raises(ValueError):
            PyramidConfig(**bad)
    with pytest.raises(ValueError):
        GridSpec(levels=0)


def test_distance_equal_to_the_cap_is_out(spark):
    mv = spark.createDataFrame([(1, 0, 0, 40_000, 0, 32.0)], "user_id long, sx long, sy long, tx long, ty long, dist_km double")
    assert min(r["level"] for r in aggregate.pyramid_edges(mv, CFG).collect()) == 2


def test_viewport_without_nodes_and_rules(spark):
    nodes = node_frame(spark, [(1, 1, 1, 3), (1, 9, 9, 1)])
    edges = spark.createDataFrame([(1, 1, 1, 9, 9, 2), (1, 1, 1, 1, 1, 1)], "level int, sx long, sy long, tx long, ty long, n long")
    seen = query.viewport_nodes(nodes, (0, 0, 90_000, 90_000), 1)
    count = lambda rule: query.viewport_edges(edges, seen, 1, rule).count()
    assert (seen.count(), count("both"), count("either"), count("source"), count("target")) == (1, 1, 2, 2, 1)
    assert query.viewport_nodes(nodes, (150_000, 0, 180_000, 30_000), 1).count() == 0


def test_served_viewports_equal_spark_ones(spark):
    mv = movements(spark, SF)
    nodes, edges = aggregate.pyramid_nodes(mv, CFG).persist(), aggregate.pyramid_edges(mv, CFG).persist()
    served = workload.Served(nodes, edges)
    for v in views(carriers.points(spark, SF), (0,), 5).collect():
        box = (v["x0"], v["y0"], v["x1"], v["y1"])
        n, e = served.viewport(box, v["level"])
        seen = query.viewport_nodes(nodes, box, v["level"])
        assert len(n) == seen.count() and len(e) == query.viewport_edges(edges, seen, v["level"]).count()


def test_all_pairs_baseline_covers_every_level(spark):
    got, want = (sorted(map(tuple, QUERIES[f"significant_nodes_{how}"](spark, SF).collect())) for how in ("all_pairs", "tiles"))
    assert got == want and {r[0] for r in got} == set(range(1, 11))


def test_every_point_is_a_probe(spark):
    asked = {r["probe_id"] for r in QUERIES["position_asof_all"](spark, SF).select("probe_id").collect()}
    assert asked == {r["point_id"] * 10 for r in carriers.points(spark, SF).select("point_id").collect()}


def test_batch_answers_all_sets_of_both_patterns(spark):
    held = [tuple(r) for r in QUERIES["significant_nodes_tiles"](spark, SF).select("level", "cx", "cy").collect()]
    want = {}
    for pattern in ("population", "hotspot"):
        for v in QUERIES[f"viewports_{pattern}"](spark, SF).collect():
            (a, b), (c, e) = query.cell_range(v["x0"], v["x1"], v["level"]), query.cell_range(v["y0"], v["y1"], v["level"])
            n = sum(lv == v["level"] and a <= x <= b and c <= y <= e for lv, x, y in held)
            if n:
                want[pattern, v["set_id"], v["query_id"]] = n
    got = {tuple(r)[:3]: r["nodes"] for r in QUERIES["viewport_result_sizes_all"](spark, SF).collect()}
    assert got == want and {k[:2] for k in got} == {(p, s) for p in ("population", "hotspot") for s in range(3)}
    assert QUERIES["viewport_batch_all"](spark, SF).count() == sum(want.values())


@pytest.mark.parametrize("name", ["auto_level", "edge_bound", "grid_levels"])
def test_grid_queries_read_their_table(spark, name):
    assert any("events.parquet" in f for f in QUERIES[name](spark, SF).inputFiles())


def test_level_of_a_box_in_every_row_equals_that_of_one_box(spark):
    rng = random.Random(5)
    boxes = [(30_000_000, 40_000_000, 58_000_000, 62_000_000), (0, 0, 399_360_000, 276_480_000), (60_000, 60_000, 60_000, 60_001), (59_999, 0, 60_001, 30_000)]
    boxes += [(x, y, x + rng.randrange(1, 10**rng.randint(1, 8)), y + rng.randrange(1, 10**rng.randint(1, 8))) for x, y in ((rng.randrange(299_000_000), rng.randrange(176_000_000)) for _ in range(60))]
    rows = [(*b, m) for b in boxes for m in (1, 100, 1000, 10_000)]
    frame = spark.createDataFrame(rows, "x0 long, y0 long, x1 long, y1 long, m int")
    for r in frame.withColumn("level", query.level_of(*map(F.col, ("x0", "y0", "x1", "y1", "m")))).collect():
        assert r["level"] == query.level_for(tuple(r)[:4], r["m"])


def nearest(es, k=10):
    p = (es - es.mean(0)) / np.maximum(es.std(0), 1e-3)
    d2 = ((p[:, None, :] - p[None, :, :]) ** 2).sum(2)
    return [[j for j in np.argsort(row, kind="stable") if j != i][:k] for i, row in enumerate(d2)]


def slow_bundles(es, near, max_angle=60.0):
    """Rounds of mutually best merges, every pair priced alone in every round."""
    n = len(es)
    groups, label = {i: [i] for i in range(n)}, list(range(n))
    way = np.arctan2(es[:, 3] - es[:, 1], es[:, 2] - es[:, 0])
    cost = {i: bundling.straight_ink(es[i : i + 1]) for i in range(n)}
    while True:
        saved = {}
        for i in range(n):
            for j in near[i]:
                g, h = sorted((label[i], label[j]))
                turn = abs((way[i] - way[j] + np.pi) % (2 * np.pi) - np.pi)
                if g != h and np.degrees(turn) <= max_angle and (g, h) not in saved:
                    saved[g, h] = cost[g] + cost[h] - bundling.bundle_ink(es[sorted(groups[g]) + sorted(groups[h])])[0]
        wish = {}
        for (g, h), s in saved.items():
            for x, y in ((g, h), (h, g)):
                if s > 1e-9 and (x not in wish or (s, -y) > (wish[x][0], -wish[x][1])):
                    wish[x] = (s, y)
        pairs = [(g, h) for g, (_, h) in wish.items() if g < h and wish.get(h, (0, -1))[1] == g]
        if not pairs:
            return label, [cost[g] for g in label]
        for g, h in pairs:
            groups[g] += groups.pop(h)
            for i in groups[g]:
                label[i] = g
            cost[g] = bundling.bundle_ink(es[sorted(groups[g])])[0]


def drawing(rng, n):
    hubs = rng.uniform(0, 60, (5, 4))
    return hubs[rng.integers(0, 5, n)] + rng.normal(0, 2, (n, 4))


def test_merges_equal_those_of_a_slow_version():
    rng = np.random.default_rng(3)
    for n in (1, 2, 40, 130):
        es = drawing(rng, n)
        near = nearest(es)
        label, ink = bundling.coalesce(es, near)
        want, cost = slow_bundles(es, near)
        assert label.tolist() == want and np.allclose(ink, cost)
        assert sum(bundling.bundle_ink(es[label == g])[0] for g in set(label.tolist())) <= bundling.straight_ink(es) + 1e-9
    assert len(bundling.coalesce(np.zeros((0, 4)), [])[0]) == 0


def test_ink_of_many_groups_equals_one_by_one():
    rng = np.random.default_rng(4)
    es, starts = drawing(rng, 60), np.array([0, 1, 5, 6, 30])
    want = [bundling.bundle_ink(part)[0] for part in np.split(es, starts[1:])]
    assert np.allclose(bundling.group_ink(es, starts), want)


def test_distributed_bundling_equals_the_one_of_arrays(spark):
    rng = np.random.default_rng(3)
    ends = {(1, 0): drawing(rng, 130), (1, 7): drawing(rng, 25), (9, 0): drawing(rng, 30), (9, 8): drawing(rng, 1)}
    rows = [(k * 1000 + i, *key, *map(float, e)) for k, (key, es) in enumerate(ends.items()) for i, e in enumerate(es)] + [(5000, 1, 0, 3.0, 3.0, 3.0, 3.0)]
    frame = spark.createDataFrame(rows, "id long, level int, tile long, x1 double, y1 double, x2 double, y2 double")
    got = {r["id"]: r for r in bundling.bundle(frame, by=("level", "tile")).collect()}
    assert len(got) == len(rows) and got[5000]["bundle"] == 5000 and got[5000]["bundle_ink"] == 0
    for k, es in enumerate(ends.values()):
        label, ink = bundling.coalesce(es, nearest(es))
        assert [got[k * 1000 + i]["bundle"] - k * 1000 for i in range(len(es))] == label.tolist()
        assert np.allclose([got[k * 1000 + i]["bundle_ink"] for i in range(len(es))], ink)
    assert bundling.bundle(frame.limit(0)).count() == 0


def test_bundling_of_a_level_in_one_drawing_with_ids_of_all_sizes(spark):
    rng = np.random.default_rng(8)
    es, ids = drawing(rng, 60), sorted(int(v) for v in rng.choice(2**62, 60, replace=False))
    frame = spark.createDataFrame([(i, 1, *map(float, e)) for i, e in zip(ids, es)], "id long, level int, x1 double, y1 double, x2 double, y2 double")
    jobs = spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs
    before = jobs()
    got = {r["id"]: r["bundle"] for r in bundling.bundle(frame).collect()}
    assert [got[i] for i in ids] == [ids[g] for g in bundling.coalesce(es, nearest(es))[0]]
    assert 0 < jobs() - before < 25


def test_proximity_of_crowded_and_lonely_points(spark):
    rng = np.random.default_rng(6)
    pts = np.concatenate([rng.normal(0, 0.01, (150, 4)), rng.uniform(-50, 50, (40, 4)), np.full((20, 4), 7.0)])
    frame = spark.createDataFrame([(i, [float(v) for v in p]) for i, p in enumerate(pts)], "id long, p array<double>")
    key = lambda df: sorted((r["id"], r["rank"], r["other"]) for r in df.collect())
    assert key(bundling.proximity_graph(frame, 5, width=1 / 16)) == key(bundling.proximity_graph(frame, 5, "all_pairs"))


def test_proximity_of_many_blocks_in_a_fixed_number_of_jobs(spark, monkeypatch):
    rng = np.random.default_rng(7)
    monkeypatch.setattr(bundling, "BLOCK_POINTS", 100)
    monkeypatch.setattr(bundling, "SAMPLED", 16)
    monkeypatch.setattr(bundling, "COLUMNS", 256)
    pts = np.concatenate([rng.integers(0, 6, (900, 4)), np.full((300, 4), 3), rng.integers(-4000, 4000, (60, 4)), rng.integers(0, 9, (40, 4))]).astype(float)
    group = np.repeat([1, 2], [1260, 40])
    rows = [(i * 7, int(g), [float(v) for v in p]) for i, (g, p) in enumerate(zip(group, pts))] + [(1, 1, None), (2, 1, [0.0, 0.0, None, 0.0]), (3, None, [0.0] * 4), (4, 3, [0.0] * 4)]
    frame = spark.createDataFrame(rows, "id long, level int, p array<double>")
    want = []
    for g in (1, 2):
        p, ids = pts[group == g], np.flatnonzero(group == g) * 7
        d2 = ((p[:, None] - p[None]) ** 2).sum(2)
        np.fill_diagonal(d2, np.inf)
        want += [(int(ids[i]), r + 1, int(ids[j])) for i, row in enumerate(d2) for r, j in enumerate(np.argsort(row, kind="stable")[:5])]
    jobs = spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs
    for method in ("all_pairs", "buckets"):
        before = jobs()
        assert sorted((r["id"], r["rank"], r["other"]) for r in bundling.proximity_graph(frame, 5, method, by=("level",)).collect()) == sorted(want)
    # the far points would have taken a dozen rounds of wider and wider cells, each of many jobs
    assert 0 < jobs() - before < 40


def test_proximity_of_blocks_plans_four_queries_on_the_driver(spark, monkeypatch):
    monkeypatch.setattr(bundling, "BLOCK_POINTS", 50)
    monkeypatch.setattr(bundling, "SAMPLED", 16)
    pts = np.concatenate([np.random.default_rng(8).integers(0, 9, (300, 4)), np.full((2, 4), 90), np.random.default_rng(9).integers(0, 9, (30, 4))]).astype(float)
    frame = spark.createDataFrame([(f"k{i:03}", str(int(i >= 302)), [float(v) for v in p]) for i, p in enumerate(pts)], "id string, drawing string, p array<double>")

    def executions():
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        return spark._jsparkSession.sharedState().statusStore().executionsCount()

    before = executions()
    found = bundling.proximity_graph(frame, 3, by=("drawing",))
    # points, large drawings, their sample, answers of blocks; it was two more, and the last plan joined the points with their reach
    assert executions() - before == 4
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    key = lambda df: sorted((r["id"], r["rank"], r["other"], r["d2"]) for r in df.collect())
    got = key(found)
    assert got == key(bundling.proximity_graph(frame, 3, "all_pairs", by=("drawing",))) and len(got) == 332 * 3


def slow_cut(values, weights, share):
    """Every cut between distinct values, tried one by one: (miss over total, position), or None."""
    total, best = float(sum(weights)), None
    for v in sorted(set(values))[1:]:
        below = float(sum(w for x, w in zip(values, weights) if x < v))
        if best is None or abs(below - share * total) / total < best[0]:
            best = abs(below - share * total) / total, v
    return best


def slow_bisect(pts, w, k, box, axis, depth=0):
    if k > 1:
        low = k // 2
        cuts = {a: slow_cut([p[a] for p in pts], w, low / k) for a in (0, 1)}
        usable = {a: c for a, c in cuts.items() if c}
        if axis == "alternate" and depth % 2 in usable:
            usable = {depth % 2: usable[depth % 2]}
        if usable:
            a = min(usable, key=lambda a: (usable[a][0], a))
            at = usable[a][1]
            x0, y0, x1, y1 = box
            halves = ((x0, y0, at, y1), (at, y0, x1, y1)) if a == 0 else ((x0, y0, x1, at), (x0, at, x1, y1))
            side = [[(p, v) for p, v in zip(pts, w) if (p[a] < at) == first] for first in (True, False)]
            return [leaf for half, part, n in zip(halves, side, (low, k - low)) for leaf in slow_bisect([p for p, _ in part], [v for _, v in part], n, half, axis, depth + 1)]
    return [box]


@pytest.mark.filterwarnings("ignore")
@pytest.mark.parametrize("axis", ["best", "alternate"])
def test_cuts_equal_those_of_trying_all(axis):
    rng = random.Random(8)
    region = CFG.grid.region
    for k in (2, 3, 6, 8, 13):
        pts = [(rng.randrange(40) * 1000, rng.randrange(25) * 1000) for _ in range(120)]
        w = [rng.randrange(1, 6) for _ in pts]
        got = partitioning.bisect(np.array(pts), k, region, axis, np.array(w))
        assert [(v.x0, v.y0, v.x1, v.y1) for v in got.leaves] == slow_bisect(pts, w, k, (0, 0, region.width, region.height), axis)


def test_a_tree_of_many_positions_is_learned_from_all_parts(spark, monkeypatch):
    """Rows in order of x: the first ones alone would put every cut on the left."""
    rows = spark.range(40_000).select((F.col("id") * 9000).alias("x"), (F.col("id") * 7919 % 27_000 * 10_000).alias("y"))
    monkeypatch.setattr(partitioning, "SAMPLE_ROWS", 4000)
    tree = partitioning.learn(rows, 8)
    assert partitioning.learn(rows.repartition(7), 8).leaves == tree.leaves
    load = metrics.load(partitioning.lookup(rows, tree)).first()
    assert load["max_over_avg"] < 1.15 and load["min_load"] > 4000


def test_rtree_of_a_batch_equals_one_by_one():
    rng = np.random.default_rng(9)
    tree = partitioning.bisect(rng.integers(0, 200_000_000, (500, 2)), 37)
    levels = partitioning.packed_rtree(tree.leaves)
    x, y = rng.integers(-1, 420_000_000, 2000), rng.integers(-1, 300_000_000, 2000)
    found = [partitioning.rtree_search(levels, i, j, i, j) for i, j in zip(x.tolist(), y.tolist())]
    assert partitioning.rtree_locate(levels, x, y).tolist() == [f[0] if f else -1 for f in found]


def test_places_of_tied_counts_and_few_nodes(spark):
    rows = [(1, x, y, n) for x, y, n in [(5, 1, 2), (4, 9, 2), (5, 0, 2), (7, 7, 1), (0, 0, 9)]] + [(2, 3, 3, 4)]
    got = {(r["level"], r["cx"], r["cy"]): (r["place"], r["before"], r["value"], r["nodes"]) for r in summarize.positions(node_frame(spark, rows)).collect()}
    assert got == {(1, 7, 7): (1, 0, 1, 5), (1, 4, 9): (2, 1, 2, 5), (1, 5, 0): (3, 1, 2, 5), (1, 5, 1): (4, 1, 2, 5), (1, 0, 0): (5, 4, 3, 5), (2, 3, 3): (1, 0, 1, 1)}
    assert summarize.positions(node_frame(spark, [])).count() == 0


@pytest.mark.parametrize("metric", ["grid_circle", "great_circle"])
def test_ranking_again_near_changes_equals_ranking_all(spark, metric):
    cfg, rng = replace(CFG, metric=metric), random.Random(10)
    old = {(lv, rng.randrange(40), rng.randrange(40)): rng.randrange(1, 9) for lv in (1, 4) for _ in range(300)}
    new = dict(old)
    for key in rng.sample(sorted(old), 6):
        new[key] += rng.randrange(1, 9)
    for _ in range(4):
        new[1, rng.randrange(40), rng.randrange(40)] = 3
    frame = lambda d: node_frame(spark, [(*k, v) for k, v in d.items()])
    changed = frame({k: v for k, v in new.items() if old.get(k) != v}).select("level", "cx", "cy")
    got = summarize.rescored(frame(new), changed, summarize.significant_nodes(frame(old), cfg), cfg)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, summarize.significant_nodes(frame(new), cfg).collect()))


def test_flows_give_the_nodes_and_edges_of_the_movements(spark):
    mv = movements(spark, SF)
    flows = aggregate.fine_flows(mv)
    rows = lambda df: sorted(map(tuple, df.select(sorted(df.columns)).collect()))
    assert rows(aggregate.nodes_of_flows(flows)) == rows(aggregate.pyramid_nodes(mv, CFG, "explode"))
    assert rows(aggregate.edges_of_flows(flows)) == rows(aggregate.pyramid_edges(mv, CFG, "explode"))


def test_bits_are_tested_in_generated_code(spark):
    mv = movements(spark, SF)
    kept = summarize.significant_nodes(aggregate.pyramid_nodes(mv))
    edges = aggregate.pyramid_edges(mv)
    passed = bloom.bloom_filter_edges(edges, kept)
    plan = passed._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" not in plan and "BroadcastHashJoin" in plan
    held, rows = bloom.filters(kept), [tuple(r) for r in edges.select("level", "sx", "sy", "tx", "ty").collect()]
    e = np.array(rows)
    ok = bloom.probe(e[:, 0], e[:, 1] << 14 | e[:, 2], held) & bloom.probe(e[:, 0], e[:, 3] << 14 | e[:, 4], held)
    assert sorted(tuple(r)[:5] for r in passed.collect()) == sorted(r for r, k in zip(rows, ok) if k)
    assert bloom.bloom_filter_edges(edges, kept.limit(0)).count() == 0


def test_plans(spark):
    mv = movements(spark, SF)
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    spark.catalog.clearCache()
    one = text(aggregate.pyramid_nodes(mv, CFG, "explode"))
    assert one.count("Exchange hashpartitioning") == 2 and "BroadcastNestedLoop" not in one and "Cartesian" not in one  # linking, counting
    nodes = aggregate.pyramid_nodes(mv, CFG).persist()
    tiled = text(summarize.significant_nodes(nodes, CFG))
    assert "BroadcastNestedLoop" not in tiled and "Cartesian" not in tiled
    scan = text(tables.table(spark, SF, "events").where("value > 10").select("event_id"))
    assert "PushedFilters: [IsNotNull(value), GreaterThan(value,10.0)]" in scan and "props" not in scan


def test_sql_surface(spark):
    sql.register_functions(spark)
    assert spark.sql("SELECT count(*) FROM cells_of(60000, 90000, 3)").first()[0] == 3
    assert spark.sql("SELECT cell_x(120000, 2)").first()[0] == 2
    assert spark.sql("SELECT count(*) FROM tiles_of(0, 0, 20, 10, 10)").first()[0] == 2


def test_text_sources(spark, tmp_path):
    (tmp_path / "p.csv").write_text("point_id,user_id,ts,x_mas,y_mas\n1,2,2024-01-01 00:00:00,3,4\nx,y\n")
    got = tables.points_csv(spark, str(tmp_path / "p.csv")).cache()
    assert got.count() == 2 and got.where("_bad is not null").count() == 1
    (tmp_path / "p.json").write_text('{"point_id":1,"user_id":2,"ts":"2024-01-01 00:00:00","x_mas":3,"y_mas":4}\n{bad\n')
    got = tables.points_json(spark, str(tmp_path / "p.json")).cache()
    assert got.where("_bad is not null").count() == 1 and got.where("x_mas = 3").count() == 1


def test_replicas_multiply_movements(spark):
    mv = movements(spark, SF)
    assert workload.replicate(mv, 3).count() == 3 * mv.count()


def test_graph_totals_of_both_carriers(spark):
    from flowlens.plans.queries_serving import totals

    assert tuple(totals(spark, movements(spark, "/root/testdata/sf0.001")).first()) == (3403, 4373, 2245, 2049)
    assert tuple(totals(spark, carriers.shipments(spark, "/root/testdata/sf0.001")).first()) == (1053, 1313, 703, 842)


def test_geocoder_checksums(spark):
    p = carriers.points(spark, "/root/testdata/sf0.01")
    got = p.agg(F.count("*"), F.sum("x_mas"), F.sum("y_mas"), F.sum(F.col("x_mas") * F.col("point_id") % 1_000_003)).first()
    assert tuple(got) == (10_000, 1_748_103_540_219, 1_370_588_269_774, 4_999_462_541)


def test_parents_children_and_look_up(spark):
    assert query.parent(3, 9, 6) == (4, 4, 3)
    kids = spark.range(1).select(grid.children(F.lit(4), F.lit(3)).alias("k")).first()["k"]
    assert {tuple(k) for k in kids} == {(8, 6), (8, 7), (9, 6), (9, 7)}
    nodes = node_frame(spark, [(1, 1, 1, 3), (1, 9, 9, 1)])
    assert query.explain_node(nodes, 1, 9, 9).first()["n"] == 1
