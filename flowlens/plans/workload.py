"""Experiment workloads that take time: step sweeps, growth with the data, and the stress test on a stored cube."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..operators import aggregate, bloom, query, serve, summarize
from ..sources import carriers
from ..sources.shared import discard, fresh_path, materialize
from .metrics import timed
from .pipeline import build
from .queries_core import movements
from .queries_serving import CUTS, hotspot_points, views

REDUCERS = (4, 8, 16, 32, 64, 128)


def prefix(mv: DataFrame, days: int) -> DataFrame:
    return mv.where(F.col("t0") < F.lit(CUTS[days]).cast("timestamp_ntz"))


def replicate(mv: DataFrame, times: int) -> DataFrame:
    """The movements so many times over, each copy with users of its own and shifted by some cells."""
    if times == 1:
        return mv
    wide = mv.withColumn("_c", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    moved = {c: F.pmod(F.col(c) + F.col("_c") * 90_000, F.lit(top).cast("long")) for c, top in (("sx", 399_360_000), ("tx", 399_360_000), ("sy", 276_480_000), ("ty", 276_480_000))}
    return wide.withColumns({"user_id": F.col("user_id") * times + F.col("_c"), **moved}).drop("_c")


def steps(mv: DataFrame, cfg: PyramidConfig = PyramidConfig(), runs: int = 1) -> dict[str, float]:
    """Seconds of the three steps; each is timed on the stored result of the one before."""
    out = {"aggregation": timed(lambda: aggregate.pyramid_nodes(mv, cfg), runs) + timed(lambda: aggregate.pyramid_edges(mv, cfg), runs)}
    nodes, edges = materialize(aggregate.pyramid_nodes(mv, cfg)), materialize(aggregate.pyramid_edges(mv, cfg))
    out["summarization"] = timed(lambda: summarize.significant_nodes(nodes, cfg), runs)
    kept = materialize(summarize.significant_nodes(nodes, cfg))
    out["filtering"] = timed(lambda: bloom.bloom_filter_edges(edges, kept, cfg.fpp), runs)
    for df in (nodes, edges, kept):
        discard(df)
    return {k: round(v, 3) for k, v in out.items()}


def step_sweep(spark: SparkSession, sf_dir: str, reducers=REDUCERS, days=(10, 20, 30), runs: int = 1) -> list[dict]:
    """Every step for every prefix and partition count, with the best count of each; adaptive coalescing is off meanwhile."""
    held = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled")}
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    out = []
    try:
        for d in days:
            mv = materialize(prefix(movements(spark, sf_dir), d))
            rows = []
            for k in reducers:
                spark.conf.set("spark.sql.shuffle.partitions", str(k))
                rows.append({"days": d, "reducers": k, **steps(mv, runs=runs)})
            best = {f"best_{s}": min(rows, key=lambda r, s=s: r[s])["reducers"] for s in ("aggregation", "summarization", "filtering")}
            out += [r | best for r in rows]
            discard(mv)
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)
    return out


def scale_up(spark: SparkSession, sf_dir: str, times=(1, 3, 10)) -> list[dict]:
    """Overall seconds as the movements multiply."""
    out = []
    for t in times:
        mv = materialize(replicate(movements(spark, sf_dir), t))
        s = steps(mv)
        out.append({"times": t, "movements": mv.count(), "overall": round(sum(s.values()), 3), **s})
        discard(mv)
    return out


class Served:
    """The summarized graph held for serving: arrays by level, sorted along x, so that a viewport is a slice and a mask. Whole period
    only; a second line of comparison beside the stored cube."""

    def __init__(self, nodes: DataFrame, edges: DataFrame):
        n, e = nodes.select("level", "cx", "cy", "n").toPandas(), edges.select("level", "sx", "sy", "tx", "ty", "n").toPandas()
        self.nodes = {lv: g.sort_values("cx")[["cx", "cy", "n"]].to_numpy() for lv, g in n.groupby("level")}
        self.edges = {lv: g.sort_values("sx")[["sx", "sy", "tx", "ty", "n"]].to_numpy() for lv, g in e.groupby("level")}

    def viewport(self, box, level: int, period=None) -> tuple[np.ndarray, np.ndarray]:
        """Nodes whose cells the box meets, and the edges with both ends among them."""
        (x0, x1), (y0, y1) = query.cell_range(box[0], box[2], level), query.cell_range(box[1], box[3], level)
        n, e = self.nodes.get(level, np.zeros((0, 3), int)), self.edges.get(level, np.zeros((0, 5), int))
        a, b = np.searchsorted(n[:, 0], (x0, x1 + 1))
        n = n[a:b]
        n = n[(n[:, 1] >= y0) & (n[:, 1] <= y1)]
        a, b = np.searchsorted(e[:, 0], (x0, x1 + 1))
        e = e[a:b]
        inside = (e[:, 1] >= y0) & (e[:, 1] <= y1) & (e[:, 2] >= x0) & (e[:, 2] <= x1) & (e[:, 3] >= y0) & (e[:, 3] <= y1)
        return n, e[inside]


#: Rows of a summarized graph up to which one process holds it as arrays, and what that holds for the published experiment.
SERVE_ROWS = 20_000_000
DURATIONS, SETS, QUERIES_A_SET = (50, 75, 100), (0, 1, 2), 2000
#: Periods that queries ask for in turn: none, a week, a day.
PERIODS = (None, ("2024-01-08", "2024-01-15"), ("2024-01-20", "2024-01-21"))


def stored_cube(spark: SparkSession, sf_dir: str, cfg: PyramidConfig = PyramidConfig()) -> tuple[str, DataFrame, DataFrame]:
    """(path of the summarized graph of every day laid out for serving, its kept nodes, its kept edges)."""
    mv = movements(spark, sf_dir)
    g = build(mv, cfg)
    kept_edges = materialize(g.kept_edges)
    node, edge = ["level", "cx", "cy"], ["level", "sx", "sy", "tx", "ty"]
    day = lambda df: df.withColumn("day", F.to_date("bin"))
    nodes = day(aggregate.pyramid_nodes(mv, cfg, time_bin="day")).join(g.kept_nodes.select(*node), node, "left_semi")
    edges = day(aggregate.pyramid_edges(mv, cfg, time_bin="day")).join(kept_edges.select(*edge), edge, "left_semi")
    path = fresh_path(spark, "cubes")
    serve.store(nodes, edges, path)
    return path, g.kept_nodes, kept_edges


def asked(spark: SparkSession, sf_dir: str, pattern: str, sets=SETS, most: int = QUERIES_A_SET) -> dict[int, list[tuple]]:
    """Queries (box, level, period) of every set of a pattern, in order; the periods take turns."""
    points = carriers.points(spark, sf_dir) if pattern == "population" else hotspot_points(spark, sf_dir)
    out: dict[int, list] = {s: [] for s in sets}
    for r in views(points, sets, most).orderBy("set_id", "query_id").collect():
        out[r["set_id"]].append(((r["x0"], r["y0"], r["x1"], r["y1"]), r["level"], PERIODS[r["query_id"] % len(PERIODS)]))
    return out


def summary(ms) -> dict:
    return {"average": round(float(np.mean(ms)), 2), "median": round(float(np.median(ms)), 2), "p90": round(float(np.quantile(ms, 0.9)), 2), "queries": len(ms)}


def service_times(ask, queries: list[tuple]) -> np.ndarray:
    """Milliseconds of every query, run one after the other."""
    out = []
    for q in queries:
        t = time.perf_counter()
        ask(*q)
        out.append((time.perf_counter() - t) * 1000)
    return np.array(out)


def response_times(service: np.ndarray, seconds: float) -> np.ndarray:
    """Milliseconds from arrival to answer when queries arrive evenly over so many seconds at one server that takes them in order:
    each query's measured service time, and the wait that those before it cause."""
    due = np.arange(len(service)) * seconds * 1000 / max(1, len(service))
    done, free = np.empty(len(service)), 0.0
    for i, (t, s) in enumerate(zip(due, service)):
        free = max(free, t) + s
        done[i] = free
    return done - due


def open_loop(ask, queries: list[tuple], seconds: float, threads: int = 8) -> np.ndarray:
    """The same by the clock: queries start when due, on a pool of threads; waiting counts."""
    start, late = time.perf_counter(), []

    def one(i: int, q: tuple) -> None:
        due = start + i * seconds / len(queries)
        time.sleep(max(0.0, due - time.perf_counter()))
        ask(*q)
        late.append((time.perf_counter() - due) * 1000)

    with ThreadPoolExecutor(threads) as pool:
        list(pool.map(lambda iq: one(*iq), enumerate(queries)))
    return np.array(late)


def stress(spark: SparkSession, sf_dir: str, durations=DURATIONS, sets=SETS, most: int = QUERIES_A_SET, by_clock=(), by_spark: int = 0) -> list[dict]:
    """The published stress test: for both patterns and every duration, sets of 2000 queries against the stored cube.

    stored: every query runs on a server opened on the cube's files; its service time enters the published arrival schedule
    (response_times), mean over the sets. arrays: the same over arrays in memory. by_clock: durations that also run by the clock
    with the first set, both patterns at once, so under twice the published load. by_spark: so many queries as one Spark job each.
    """
    path, nodes, edges = stored_cube(spark, sf_dir)
    arrays = Served(nodes, edges) if nodes.count() + edges.count() <= SERVE_ROWS else None
    out, servers = [], {}
    for pattern in ("population", "hotspot"):
        queries = asked(spark, sf_dir, pattern, sets, most)
        server = serve.CubeServer(path)
        servers[pattern] = server, queries[sets[0]]
        stored = {s: service_times(server.viewport, q) for s, q in queries.items()}
        held = {s: service_times(arrays.viewport, q) for s, q in queries.items()} if arrays else {}
        mean = lambda runs: {"queries": sum(r["queries"] for r in runs)} | {k: round(float(np.mean([r[k] for r in runs])), 2) for k in ("average", "median", "p90")}
        for seconds in durations:
            row = {"pattern": pattern, "seconds": seconds, "sets": len(sets), "stored": mean([summary(response_times(v, seconds)) for v in stored.values()])}
            if held:
                row["arrays"] = mean([summary(response_times(v, seconds)) for v in held.values()])
            out.append(row)
        out[-1] |= {"row_groups_read": server.reads, "cube_rows": server.rows, "cache_mb": server.bytes >> 20}
        if by_spark:
            job = lambda box, level, period: query.viewport_edges(edges, query.viewport_nodes(nodes, box, level), level).toArrow()
            out[-1]["spark_job"] = summary(service_times(job, queries[sets[0]][:by_spark]))
    for seconds in by_clock:
        with ThreadPoolExecutor(len(servers)) as pool:
            runs = {p: pool.submit(open_loop, server.viewport, q, seconds) for p, (server, q) in servers.items()}
        for row in out:
            if row["seconds"] == seconds:
                row["by_clock"] = summary(runs[row["pattern"]].result())
    return out


def graph_sizes(spark: SparkSession, sf_dir: str, days=(10, 20, 30)) -> list[dict]:
    """Nodes and edges before and after for growing periods, with neighbourhoods of cells in a disc and by great-circle distance."""
    out = []
    for metric in ("grid_circle", "great_circle"):
        for d in days:
            g = build(prefix(movements(spark, sf_dir), d), PyramidConfig(metric=metric))
            n, e, kn, ke = (x.count() for x in (g.nodes, g.edges, g.kept_nodes, g.kept_edges))
            out.append({"metric": metric, "days": d, "nodes": n, "kept_nodes": kn, "nodes_share": round(kn / n, 4), "edges": e, "kept_edges": ke, "edges_share": round(ke / e, 4)})
    return out


def ablations(spark: SparkSession, sf_dir: str, runs: int = 1, times: int = 1) -> dict[str, dict[str, float]]:
    """Seconds of every alternative of a step on the same stored input: look-ups, combiners, edge filters and their false-positive
    shares, neighbourhood strategies, scan split sizes. times: copies of the movements that the steps work on."""
    from ..operators import partitioning
    from .queries_core import work_tree

    cfg = PyramidConfig()
    mv = materialize(replicate(movements(spark, sf_dir), times))
    points = materialize(carriers.points(spark, sf_dir).select("point_id", F.col("x_mas").alias("x"), F.col("y_mas").alias("y")))
    tree = work_tree(spark, sf_dir, 64)
    out = {"lookup": {m: timed(lambda m=m: partitioning.lookup(points, tree, m), runs) for m in ("cut_tree", "rtree", "linear")}}
    out["combiner"] = {s: timed(lambda s=s: aggregate.pyramid_nodes(mv, cfg, s), runs) for s in ("rollup", "explode", "in_task", "none", *(("builtin",) if times == 1 else ()))}
    nodes, edges = materialize(aggregate.pyramid_nodes(mv, cfg)), materialize(aggregate.pyramid_edges(mv, cfg))
    out["neighbourhood"] = {s: timed(lambda s=s: summarize.significant_nodes(nodes, cfg, s), runs) for s in ("tiles", "offsets")}
    out["neighbourhood"]["leaves"] = timed(lambda: summarize.significant_nodes(nodes, cfg, "leaves", tree), runs)
    out["neighbourhood"]["great_circle"] = timed(lambda: summarize.significant_nodes(nodes, PyramidConfig(metric="great_circle")), runs)
    kept = materialize(summarize.significant_nodes(nodes, cfg))
    out["edge_filter"] = {f"bloom_{p}": timed(lambda p=p: bloom.bloom_filter_edges(edges, kept, p), runs) for p in (0.1, 0.01, 0.001)}
    out["edge_filter"] |= {h or "join": timed(lambda h=h: bloom.join_filter_edges(edges, kept, h), runs) for h in (None, "broadcast", "merge", "shuffle_hash")}
    out["passed"] = {f"bloom_{p}": bloom.bloom_filter_edges(edges, kept, p).count() for p in (0.1, 0.01, 0.001)} | {"join": bloom.join_filter_edges(edges, kept).count(), "all": edges.count()}
    held = spark.conf.get("spark.sql.files.maxPartitionBytes")
    try:
        out["split_bytes"] = {}
        for n in (64 << 10, 1 << 20, 128 << 20):
            spark.conf.set("spark.sql.files.maxPartitionBytes", str(n))
            out["split_bytes"][str(n)] = timed(lambda: aggregate.pyramid_nodes(movements(spark, sf_dir), cfg), runs)
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", held)
    return {k: {m: round(v, 3) for m, v in d.items()} for k, d in out.items()}


def pruning(cube_nodes: DataFrame, box, level: int, period=None) -> tuple[int, int]:
    """Files that a viewport over a stored cube reads, and all its files."""
    files = lambda df: df.select(F.input_file_name().alias("f")).distinct().count()
    (cx0, cx1), (cy0, cy1) = query.cell_range(box[0], box[2], level), query.cell_range(box[1], box[3], level)
    lo, hi = query.morton_interval(cx0, cy0, cx1, cy1)
    seen = cube_nodes.where((F.col("level") == level) & F.col("morton").between(lo, hi))
    if period:
        seen = seen.where((F.col("bin") >= period[0]) & (F.col("bin") < period[1]))
    return files(seen), files(cube_nodes)
