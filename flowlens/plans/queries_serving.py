"""Queries of partitioning, serving, workloads and the general operators that users of the graph need."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions import geo, grid
from ..operators import aggregate, bundling, cube, partitioning, query, serve, summarize, trajectory
from ..operators.summarize import positions
from ..sources import carriers
from ..sources.shared import fresh_path, materialize
from ..sources.tables import table
from . import metrics
from .oracle_sql import bisection, hash_placed, with_
from .pipeline import build
from .queries_core import edges, held_nodes, kept, movements, nodes, work_sample, work_tree

QUERIES, ORACLES = {}, {}
CFG = PyramidConfig()


def query_(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# --- partitioning. A fixed tree (cuts of a 16-leaf tree learned at the test size) stands for the data-dependent one in the oracle.

FIXED_X = (31_000_000, 62_000_000, 97_000_000, 142_000_000, 171_000_000, 219_000_000, 296_000_000)


def fixed_tree() -> partitioning.PartitionTree:
    """Eight stripes by fixed cuts, with their comparison tree."""
    region = CFG.grid.region
    bounds = (0, *FIXED_X, region.width)
    leaves = [partitioning.Leaf(i, a, 0, b, region.height) for i, (a, b) in enumerate(zip(bounds, bounds[1:]))]

    def grow(lo: int, hi: int):
        if hi - lo == 1:
            return lo
        mid = (lo + hi) // 2
        return (0, bounds[mid], grow(lo, mid), grow(mid, hi))

    return partitioning.PartitionTree(leaves, grow(0, len(leaves)))


LEAF = "CAST(" + " + ".join(f"CASE WHEN x_mas >= {c} THEN 1 ELSE 0 END" for c in FIXED_X) + " AS INTEGER)"
for _key, _how in (("partition_lookup_tree", "cut_tree"), ("partition_lookup_rtree", "rtree"), ("partition_lookup_linear", "linear")):
    query_(with_("pts", f"SELECT point_id, {LEAF} AS leaf FROM pts"), _key)(
        lambda spark, d, how=_how: partitioning.lookup(carriers.points(spark, d).select("point_id", F.col("x_mas").alias("x"), F.col("y_mas").alias("y")), fixed_tree(), how).select("point_id", "leaf"))


@query_(with_("mv", "SELECT movement_id, user_id FROM mv WHERE (movement_id * 48271 + 42) % 2147483647 % 10000 < 500"))
def partition_sample(spark, d):
    return partitioning.sample(movements(spark, d), 0.05).select("movement_id", "user_id")


_bounds = (0, *FIXED_X, 399_360_000)
_values = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(zip(_bounds, _bounds[1:])))


@query_(with_("nodes", f""", leaves(leaf, x0, x1) AS (VALUES {_values}), c AS (SELECT *, cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS x, 3 * (30000 << (level - 1)) AS off FROM nodes)
    SELECT level, cx, cy, leaf FROM c JOIN leaves ON x0 <= x + off AND x1 > x - off""".lstrip()))
def neighbor_partitions(spark, d):
    n = nodes(spark, d).withColumns({"x": grid.centre(F.col("cx"), F.col("level")), "y": grid.centre(F.col("cy"), F.col("level")), "off": F.call_function("shiftleft", F.lit(90_000).cast("long"), F.col("level") - 1)})
    return partitioning.leaves_within(n, fixed_tree(), "off").select("level", "cx", "cy", "leaf")


#: The sample of work_tree() in SQL: x, y and w of cells that a fifth of the movements touch.
SAMPLED = """SELECT cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS x, cy * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS y, {w} AS w
    FROM wide WHERE (movement_id * 48271 + 42) % 2147483647 % 10000 < 2000 GROUP BY level, cx, cy"""
#: What eight map tasks would send for the nodes, with the positions that look-ups take.
PARTIAL = "SELECT DISTINCT movement_id % 8 AS task, level, cx, cy, cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS x, cy * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS y FROM wide"


def bisected(k: int, axis: str = "best", w: str = "1", out: str = "leaves") -> str:
    return bisection(SAMPLED.format(w=w), k, axis, out)


for _key, _k, _axis, _w in (("bisection_leaves", 16, "best", None), ("bisection_leaves_k6", 6, "best", None), ("bisection_alternating", 16, "alternate", None), ("bisection_weighted", 16, "best", "n")):
    query_(with_("wide", ", " + bisected(_k, _axis, "count(*)" if _w else "1") + " SELECT * FROM leaves"), _key)(lambda spark, d, k=_k, axis=_axis, w=_w: work_tree(spark, d, k, axis, w).frame(spark))


def partial_records(spark, d) -> DataFrame:
    """What eight map tasks would send for the nodes: one record per task, level and cell; task = event id modulo 8."""
    ends = aggregate.endpoints(movements(spark, d).withColumn("task", F.col("movement_id") % 8), ("task",)).withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(10))))
    cells = ends.select("task", "level", grid.cell(F.col("x"), F.col("level")).alias("cx"), grid.cell(F.col("y"), F.col("level")).alias("cy")).distinct()
    return cells.withColumns({"x": grid.centre(F.col("cx"), F.col("level")), "y": grid.centre(F.col("cy"), F.col("level"))})


LOADS = """CAST(sum(c) AS BIGINT) AS records, round(avg(c), 6) AS avg_load, round(stddev_pop(c), 6) AS std_load, min(c) AS min_load, max(c) AS max_load,
    round(max(c) / avg(c), 6) AS max_over_avg, round(stddev_pop(c) / avg(c), 6) AS std_over_avg"""
LOAD_COLUMNS = ("avg_load", "std_load", "max_over_avg", "std_over_avg")
REDUCERS = (8, 16, 32, 64)
STRIPE = "cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2"
#: Keys of a range placement: level, then the Morton key of the cell.
MORTON = "(CAST(level AS BIGINT) << 28) | " + " | ".join(f"(((cx >> {i}) & 1) << {2 * i}) | (((cy >> {i}) & 1) << {2 * i + 1})" for i in range(14))


def load_sql(method: str, k: int) -> str:
    """Load of K partitions by a placement method, as one row."""
    if method == "stripes":
        each = f"SELECT x // {-(-399_360_000 // k)} AS p, count(*) AS c FROM partial GROUP BY 1"
    elif method == "hash":
        each = f"SELECT slot AS p, count(*) AS c FROM {hash_placed('(SELECT level, cx, cy FROM partial)', k)} GROUP BY 1"
    elif method == "range":
        bounds = f"SELECT list(key ORDER BY key) AS l FROM (SELECT DISTINCT {MORTON} AS key FROM wide WHERE (movement_id * 48271 + 42) % 2147483647 % 10000 < 2000)"
        reached = " + ".join(f"CASE WHEN {MORTON} >= l[{i} * len(l) // {k} + 1] THEN 1 ELSE 0 END" for i in range(1, k))
        each = f"SELECT {reached} AS p, count(*) AS c FROM partial, ({bounds}) GROUP BY 1"
    else:
        each = f"SELECT leaf AS p, count(*) AS c FROM partial r JOIN {method}_{k} l ON r.x >= l.x0 AND r.x < l.x1 AND r.y >= l.y0 AND r.y < l.y1 GROUP BY 1"
    return f"SELECT '{method}' AS method, {k} AS reducers, {LOADS} FROM ({each})"


TREES = {"best": ("best", None), "alternate": ("alternate", None), "weighted": ("best", "n")}


def loads_sql(cases: list[tuple[str, int]]) -> str:
    need = "".join(", " + bisected(k, TREES[m][0], "count(*)" if TREES[m][1] else "1", f"{m}_{k}") for m, k in cases if m in TREES)
    return with_("wide", f", partial AS MATERIALIZED ({PARTIAL}){need} " + " UNION ALL ".join(load_sql(m, k) for m, k in cases))


def placed(records: DataFrame, work: DataFrame, method: str, k: int) -> DataFrame:
    """The records with p, their partition of k. work: the sample (x, y, n, key) that trees and ranges are learned from."""
    if method == "stripes":
        return records.withColumn("p", F.floor(F.col("x") / -(-CFG.grid.region.width // k)))
    if method == "hash":
        return records.withColumn("p", partitioning.hash_slot(k, "level", "cx", "cy"))
    if method == "range":
        key = F.shiftleft(F.col("level").cast("long"), 28).bitwiseOR(grid.morton(F.col("cx"), F.col("cy")))
        return records.withColumn("p", partitioning.by_bounds(key, partitioning.range_bounds(work.select("key"), k)))
    axis, weight = TREES[method]
    return partitioning.lookup(records, partitioning.learn(work, k, axis=axis, weight=weight)).withColumn("p", F.col("leaf"))


def load_row(records: DataFrame, work: DataFrame, method: str, k: int) -> DataFrame:
    got = metrics.load(placed(records, work, method, k), "p").withColumns({c: F.round(c, 6) for c in LOAD_COLUMNS})
    return got.select(F.lit(method).alias("method"), F.lit(k).alias("reducers"), "*")


def _load(method: str, k: int):
    return lambda spark, d: load_row(partial_records(spark, d), work_sample(spark, d), method, k).drop("method", "reducers")


for _k in REDUCERS:
    for _method, _name in (("best", f"load_stats_{_k}"), ("stripes", f"load_stats_stripes_{_k}")):
        query_(f"SELECT * EXCLUDE (method, reducers) FROM ({loads_sql([(_method, _k)])})", _name)(_load(_method, _k))

METHODS = ("best", "weighted", "alternate", "stripes", "hash", "range")


@query_(loads_sql([(m, k) for m in METHODS for k in REDUCERS]))
def load_stats_methods(spark, d):
    """Reducer load of every placement method and partition count: records, mean, deviation, least, most, and both over the mean."""
    records, work = materialize(partial_records(spark, d)), materialize(work_sample(spark, d))
    return reduce(DataFrame.unionByName, [load_row(records, work, m, k) for m in METHODS for k in REDUCERS])


def per_partition(df: DataFrame) -> DataFrame:
    """Rows of every Spark partition that has any."""
    return df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("c"))


@query_(with_("wide", f", partial AS MATERIALIZED ({PARTIAL}), {bisected(16)} SELECT leaf AS p, count(*) AS c FROM partial r JOIN leaves l ON r.x >= l.x0 AND r.x < l.x1 AND r.y >= l.y0 AND r.y < l.y1 GROUP BY 1"))
def placement_load(spark, d):
    """Rows of the Spark partitions after placing every leaf in its own."""
    return per_partition(partitioning.place(partitioning.lookup(partial_records(spark, d), work_tree(spark, d)), 16))


@query_(with_("wide", f"SELECT CAST(slot AS INTEGER) AS p, count(*) AS c FROM {hash_placed(f'(SELECT level, cx, cy FROM ({PARTIAL}))', 16)} GROUP BY 1"))
def placement_load_hash(spark, d):
    """Rows of the Spark partitions by default hash placement."""
    return per_partition(partitioning.place(partial_records(spark, d), 16, "hash"))


@query_(with_("wide", f"SELECT CAST(count(*) AS BIGINT) AS records, 16 AS partitions, TRUE AS ordered FROM ({PARTIAL})"))
def placement_load_range(spark, d):
    """Spark's own range placement, whose bounds come from its sampling: all records, in so many partitions, none overlapping another."""
    key = F.shiftleft(F.col("level").cast("long"), 28).bitwiseOR(grid.morton(F.col("cx"), F.col("cy")))
    spans = partitioning.place(partial_records(spark, d), 16, "range").groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("c"), F.min(key).alias("lo"), F.max(key).alias("hi"))
    after = spans.withColumn("next", F.lead("lo").over(Window.partitionBy(F.lit(0)).orderBy("p")))
    return after.agg(F.sum("c").alias("records"), F.count("*").cast("int").alias("partitions"), F.bool_and(F.coalesce(F.col("hi") < F.col("next"), F.lit(True))).alias("ordered"))


@query_(with_("wide", f"SELECT CAST(count(*) AS BIGINT) AS increments, (SELECT count(*) FROM ({PARTIAL})) AS partial_records FROM wide"))
def combiner_reduction(spark, d):
    inc = movements(spark, d).agg((F.count("*") * 20).alias("increments"))
    return inc.crossJoin(partial_records(spark, d).agg(F.count("*").alias("partial_records")))


@query_(with_("nodes", f""", leaves(leaf, x0, x1) AS (VALUES {_values}), c AS (SELECT *, cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2 AS x, 3 * (30000 << (level - 1)) AS off FROM nodes)
    SELECT level, count(*) AS copies, count(DISTINCT (cx, cy)) AS nodes FROM c JOIN leaves ON x0 <= x + off AND x1 > x - off GROUP BY level""".lstrip()))
def replication_factor(spark, d):
    return neighbor_partitions(spark, d).groupBy("level").agg(F.count("*").alias("copies"), F.countDistinct("cx", "cy").alias("nodes"))


# --- sizes and workloads


@query_(with_("nodes edges kept kedges lv", "SELECT level, " + ", ".join(f"(SELECT count(*) FROM {t} t WHERE t.level = lv.level) AS {a}" for t, a in (("nodes", "nodes"), ("edges", "edges"), ("kept", "kept_nodes"), ("kedges", "kept_edges"))) + " FROM lv"))
def graph_size_by_level(spark, d):
    g = build(movements(spark, d))
    count = lambda df, c: df.groupBy("level").agg(F.count("*").alias(c))
    parts = [count(g.nodes, "nodes"), count(g.edges, "edges"), count(g.kept_nodes, "kept_nodes"), count(g.kept_edges, "kept_edges")]
    out = spark.range(1, 11).select(F.col("id").cast("int").alias("level"))
    for p in parts:
        out = out.join(p, "level", "left")
    return out.na.fill(0)


TOTALS = ", ".join(f"(SELECT count(*) FROM {t}) AS {a}" for t, a in (("nodes", "nodes"), ("edges", "edges"), ("kept", "kept_nodes"), ("kedges", "kept_edges")))


def totals(spark, mv: DataFrame) -> DataFrame:
    """One row: nodes and edges over all levels, before and after."""
    g = build(mv)
    one = lambda df, c: df.agg(F.count("*").alias(c))
    return reduce(DataFrame.crossJoin, [one(g.nodes, "nodes"), one(g.edges, "edges"), one(g.kept_nodes, "kept_nodes"), one(g.kept_edges, "kept_edges")])


@query_(with_("nodes edges kept kedges", f"SELECT {TOTALS}", "ships"))
def graph_size_shipments(spark, d):
    """The second carrier: few sources, heavy repeated flows."""
    return totals(spark, carriers.shipments(spark, d))


CUTS = {10: "2024-01-11", 20: "2024-01-21", 30: "2024-01-31"}


@query_(with_("pts", " UNION ALL ".join(f"SELECT {n} AS days, count(*) AS posts, count(DISTINCT user_id) AS users, count(*) - count(DISTINCT user_id) AS movements FROM pts WHERE ts < TIMESTAMP '{t}'" for n, t in CUTS.items())))
def prefix_statistics(spark, d):
    p = carriers.points(spark, d)
    one = lambda n, t: p.where(F.col("ts") < F.lit(t).cast("timestamp_ntz")).agg(F.lit(n).alias("days"), F.count("*").alias("posts"), F.countDistinct("user_id").alias("users")).withColumn("movements", F.col("posts") - F.col("users"))
    return reduce(DataFrame.unionByName, [one(n, t) for n, t in CUTS.items()])


@query_(" UNION ALL ".join("SELECT * FROM (" + with_("nodes edges kept kedges", f"SELECT {n} AS days, {TOTALS}", f"(SELECT * FROM mv0 WHERE t0 < TIMESTAMP '{t}')") + ")" for n, t in CUTS.items()))
def graph_size_prefixes(spark, d):
    """Graph size before and after for growing periods."""
    mv = movements(spark, d)
    one = lambda n, t: totals(spark, mv.where(F.col("t0") < F.lit(t).cast("timestamp_ntz"))).select(F.lit(n).alias("days"), "*")
    return reduce(DataFrame.unionByName, [one(n, t) for n, t in CUTS.items()])


@query_(with_("flows lv", """, pairs AS (SELECT DISTINCT level, least((sx, sy), (tx, ty)) AS a, greatest((sx, sy), (tx, ty)) AS b FROM flows WHERE sx <> tx OR sy <> ty),
    seen AS (SELECT level, count(*) AS pairs FROM pairs GROUP BY level),
    bound AS (SELECT level, CAST(ceil(13312.0 / (1 << (level - 1))) * ceil(9216.0 / (1 << (level - 1))) AS BIGINT) AS cells FROM lv)
    SELECT CAST(level AS INTEGER) AS level, cells, CAST(cells * (cells - 1) // 2 AS BIGINT) AS max_pairs, CAST(coalesce(pairs, 0) AS BIGINT) AS pairs FROM bound LEFT JOIN seen USING (level)""".lstrip()))
def edge_bound(spark, d):
    """Undirected edges without loops that a level's cells allow, and how many of them the movements make."""
    seen = aggregate.pyramid_edges(movements(spark, d), replace(CFG, uncapped=True), "rollup", directed=False, loops=False).groupBy("level").agg(F.count("*").alias("pairs"))
    sizes = [(lv, CFG.grid.shape(lv)[0] * CFG.grid.shape(lv)[1]) for lv in range(1, 11)]
    bound = spark.createDataFrame([(lv, c, metrics.edge_bound(c)) for lv, c in sizes], "level int, cells long, max_pairs long")
    return bound.join(seen, "level", "left").withColumn("pairs", F.coalesce("pairs", F.lit(0).cast("long")))


@query_(with_("flows", "SELECT CAST(level AS INTEGER) AS level, count(*) FILTER (dist_km < cap) AS shown, count(*) FILTER (dist_km >= cap) AS hidden FROM flows GROUP BY level"))
def cap_effect(spark, d):
    mv = movements(spark, d).withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(10))))
    cap = grid.by_level(CFG.caps, F.col("level"))
    return mv.groupBy("level").agg(F.count_if(F.col("dist_km") < cap).alias("shown"), F.count_if(F.col("dist_km") >= cap).alias("hidden"))


def views(points: DataFrame, sets: tuple[int, ...] = (0, 1, 2), most: int = 2000) -> DataFrame:
    """Viewports centred on points drawn by an arithmetic hash, so crowded places recur: set_id, query_id, x0, y0, x1, y1, level.

    Each set keeps its points of least hash by a bounded top-k, so only that many rows are numbered.
    """
    h = lambda s: (F.col("point_id") * 69_621 + 7_919 * s) % F.lit(2_147_483_647).cast("long")
    few = [points.select("point_id", "x_mas", "y_mas", F.lit(s).alias("set_id"), h(s).alias("h")).orderBy("h", "point_id").limit(most) for s in sets]
    w = Window.partitionBy("set_id").orderBy("h", "point_id")
    p = reduce(DataFrame.unionByName, few).withColumn("query_id", F.row_number().over(w) - 1).withColumn("level", (F.col("h") % 10 + 1).cast("int"))
    size = F.call_function("shiftleft", F.lit(30_000).cast("long"), F.col("level") - 1)
    region = CFG.grid.region
    zero = F.lit(0).cast("long")
    return p.select("set_id", "query_id", F.greatest(F.col("x_mas") - size * 16, zero).alias("x0"), F.greatest(F.col("y_mas") - size * 9, zero).alias("y0"),
                    F.least(F.col("x_mas") + size * 16, F.lit(region.width).cast("long")).alias("x1"), F.least(F.col("y_mas") + size * 9, F.lit(region.height).cast("long")).alias("y1"), "level")


VIEW = "SELECT set_id, query_id, x0, y0, x1, y1, level FROM views"


@query_(with_("views", VIEW))
def viewports_population(spark, d):
    return views(carriers.points(spark, d))


def hotspot_points(spark, d) -> DataFrame:
    p = carriers.points(spark, d)
    at = p.withColumns({"hx": grid.cell(F.col("x_mas"), 8), "hy": grid.cell(F.col("y_mas"), 8)})
    top = at.groupBy("hx", "hy").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "hx", "hy").limit(1)
    return at.join(F.broadcast(top), ["hx", "hy"], "left_semi")


HOT = with_("views", VIEW).replace("FROM pts, (SELECT unnest([0, 1, 2])", "FROM (SELECT * FROM pts WHERE ((x_mas // 30000) >> 7, (y_mas // 30000) >> 7) = (SELECT ((x_mas // 30000) >> 7, (y_mas // 30000) >> 7) FROM pts GROUP BY ALL ORDER BY count(*) DESC, (x_mas // 30000) >> 7, (y_mas // 30000) >> 7 LIMIT 1)), (SELECT unnest([0, 1, 2])")


@query_(HOT.replace("SELECT ((x_mas // 30000) >> 7, (y_mas // 30000) >> 7) FROM pts GROUP BY ALL ORDER BY count(*) DESC, (x_mas // 30000) >> 7, (y_mas // 30000) >> 7 LIMIT 1", "SELECT (a, b) FROM (SELECT (x_mas // 30000) >> 7 AS a, (y_mas // 30000) >> 7 AS b, count(*) AS c FROM pts GROUP BY ALL ORDER BY c DESC, a, b LIMIT 1)"))
def viewports_hotspot(spark, d):
    return views(hotspot_points(spark, d))


INSIDE = "n.level = v.level AND cx BETWEEN x0 // (30000 << (v.level - 1)) AND greatest((x1 - 1) // (30000 << (v.level - 1)), 0) AND cy BETWEEN y0 // (30000 << (v.level - 1)) AND greatest((y1 - 1) // (30000 << (v.level - 1)), 0)"
FIRST = "(SELECT * FROM views WHERE set_id = 0 AND query_id < 50)"


@query_(with_("views kept", f"SELECT set_id, query_id, v.level, cx, cy, n FROM {FIRST} v JOIN kept n ON {INSIDE}"))
def viewport_batch(spark, d):
    v = views(carriers.points(spark, d), (0,), 50)
    return query.viewports(kept(spark, d), v)


@query_(with_("views kept", f"SELECT set_id, query_id, count(*) AS nodes FROM {FIRST} v JOIN kept n ON {INSIDE} GROUP BY ALL"))
def viewport_result_sizes(spark, d):
    return viewport_batch(spark, d).groupBy("set_id", "query_id").agg(F.count("*").alias("nodes"))


def answers(spark, d) -> DataFrame:
    """All viewports of both patterns, three sets of 2000 each, in one batch."""
    patterns = {"population": carriers.points(spark, d), "hotspot": hotspot_points(spark, d)}
    asked = [views(p).withColumn("set_id", F.concat_ws("/", F.lit(name), F.col("set_id"))) for name, p in patterns.items()]
    return query.viewports(kept(spark, d), reduce(DataFrame.unionByName, asked))


def by_pattern(got: DataFrame) -> DataFrame:
    return got.withColumn("pattern", F.split_part("set_id", F.lit("/"), F.lit(1))).withColumn("set_id", F.split_part("set_id", F.lit("/"), F.lit(2)).cast("int"))


@query_()
def viewport_batch_all(spark, d):
    """Without SQL; tests compare with a count in plain Python."""
    return by_pattern(answers(spark, d)).select("pattern", "set_id", "query_id", "level", "cx", "cy", "n")


@query_()
def viewport_result_sizes_all(spark, d):
    return by_pattern(answers(spark, d).groupBy("set_id", "query_id").agg(F.count("*").alias("nodes"))).select("pattern", "set_id", "query_id", "nodes")


#: A view over the busiest south-west anchors.
BOX, LEVEL = (30_000_000, 40_000_000, 200_000_000, 200_000_000), 6
_c = 30_000 << (LEVEL - 1)
IN_BOX = f"level = {LEVEL} AND cx BETWEEN {BOX[0] // _c} AND {-(-BOX[2] // _c) - 1} AND cy BETWEEN {BOX[1] // _c} AND {-(-BOX[3] // _c) - 1}"


def _edges_in(source: str, rule: str = "AND") -> str:
    both = " AND ".join(f"EXISTS (SELECT 1 FROM seen s WHERE s.cx = e.{a} AND s.cy = e.{b})" for a, b in (("sx", "sy"), ("tx", "ty")))
    return f"SELECT level, sx, sy, tx, ty, n FROM {source} e WHERE level = {LEVEL} AND " + (both if rule == "AND" else "(" + both.replace(" AND EXISTS", " OR EXISTS") + ")")


@query_(with_("kept", f"SELECT level, cx, cy, n FROM kept WHERE {IN_BOX}"))
def viewport_nodes(spark, d):
    return query.viewport_nodes(query.with_morton(kept(spark, d)), BOX, LEVEL).select("level", "cx", "cy", "n")


@query_(with_("kedges", f", seen AS (SELECT cx, cy FROM kept WHERE {IN_BOX}) " + _edges_in("kedges")))
def viewport_edges(spark, d):
    g = build(movements(spark, d))
    return query.viewport_edges(g.kept_edges, query.viewport_nodes(g.kept_nodes, BOX, LEVEL), LEVEL).select("level", "sx", "sy", "tx", "ty", "n")


@query_(with_("kedges", f", seen AS (SELECT cx, cy FROM kept WHERE {IN_BOX}) " + _edges_in("kedges", "OR")))
def viewport_edges_either(spark, d):
    g = build(movements(spark, d))
    return query.viewport_edges(g.kept_edges, query.viewport_nodes(g.kept_nodes, BOX, LEVEL), LEVEL, "either").select("level", "sx", "sy", "tx", "ty", "n")


@query_(with_("edges nodes", f", seen AS (SELECT cx, cy FROM nodes WHERE {IN_BOX}) " + _edges_in("edges")))
def viewport_raw(spark, d):
    return query.viewport_raw(movements(spark, d), BOX, LEVEL)[1].select("level", "sx", "sy", "tx", "ty", "n")


@query_(with_("wide", f"SELECT level, cx, cy, count(*) AS n FROM wide WHERE {IN_BOX} AND t0 >= TIMESTAMP '2024-01-05' AND t0 < TIMESTAMP '2024-01-12' GROUP BY ALL"))
def viewport_period(spark, d):
    days = aggregate.pyramid_nodes(movements(spark, d), time_bin="day").withColumn("bin", F.date_format("bin", "yyyy-MM-dd"))
    return query.viewport_nodes(days, BOX, LEVEL, ("2024-01-05", "2024-01-12"))


@query_(with_("wide", "SELECT strftime(t0, '%Y-%m-%d') AS bin, CAST(level AS INTEGER) AS level, count(DISTINCT (cx, cy)) AS cells, count(*) AS n FROM wide GROUP BY ALL"))
def cube_roundtrip(spark, d):
    path = fresh_path(spark, "cubes")
    mv = movements(spark, d)
    day = lambda df: df.withColumn("bin", F.date_format("bin", "yyyy-MM-dd"))
    cube.write(day(aggregate.pyramid_nodes(mv, time_bin="day")), day(aggregate.pyramid_edges(mv, time_bin="day")), path)
    return cube.open_cube(spark, path).nodes.groupBy("bin", "level").agg(F.count("*").alias("cells"), F.sum("n").alias("n"))


VIEW_CELLS = (100, 1000, 10_000)


@query_(with_("pts lv", f""", boxes AS (SELECT user_id, min(x_mas) AS x0, min(y_mas) AS y0, max(x_mas) AS x1, max(y_mas) AS y1 FROM pts GROUP BY user_id),
    fits AS (SELECT user_id, max_cells, min(level) FILTER ((x1 // (30000 << (level - 1)) - x0 // (30000 << (level - 1)) + 1) * (y1 // (30000 << (level - 1)) - y0 // (30000 << (level - 1)) + 1) <= max_cells) AS level
    FROM boxes, lv, (SELECT unnest({list(VIEW_CELLS)}) AS max_cells) GROUP BY user_id, max_cells)
    SELECT user_id, CAST(max_cells AS INTEGER) AS max_cells, CAST(coalesce(level, 10) AS INTEGER) AS level FROM fits""".lstrip()))
def auto_level(spark, d):
    """The level that opens on the places of every user, for views of three sizes."""
    boxes = carriers.points(spark, d).groupBy("user_id").agg(F.min("x_mas").alias("x0"), F.min("y_mas").alias("y0"), (F.max("x_mas") + 1).alias("x1"), (F.max("y_mas") + 1).alias("y1"))
    sizes = boxes.withColumn("max_cells", F.explode(F.array(*map(F.lit, VIEW_CELLS))))
    return sizes.select("user_id", "max_cells", query.level_of(*map(F.col, ("x0", "y0", "x1", "y1", "max_cells"))).alias("level"))


@query_(with_("nodes", ", top AS (SELECT cx, cy FROM nodes WHERE level = 8 ORDER BY n DESC, cx, cy LIMIT 1) SELECT n.level, n.cx, n.cy, n.n FROM nodes n, top WHERE n.level = 7 AND n.cx >> 1 = top.cx AND n.cy >> 1 = top.cy"))
def drill_down(spark, d):
    n = held_nodes(spark, d)
    top = n.where("level = 8").orderBy(F.desc("n"), "cx", "cy").first()
    return query.drill(n, 8, top["cx"], top["cy"]).select("level", "cx", "cy", "n")


@query_(with_("edges mv", ", top AS (SELECT sx, sy, tx, ty FROM edges WHERE level = 6 AND (sx <> tx OR sy <> ty) ORDER BY n DESC, sx, sy, tx, ty LIMIT 1) SELECT movement_id, m.user_id FROM mv m, top t WHERE (m.sx // 30000) >> 5 = t.sx AND (m.sy // 30000) >> 5 = t.sy AND (m.tx // 30000) >> 5 = t.tx AND (m.ty // 30000) >> 5 = t.ty AND dist_km < 1024"))
def edge_members(spark, d):
    t = edges(spark, d).where("level = 6 and (sx <> tx or sy <> ty)").orderBy(F.desc("n"), "sx", "sy", "tx", "ty").first()
    return query.members(movements(spark, d), (6, t["sx"], t["sy"], t["tx"], t["ty"])).select("movement_id", "user_id")


@query_(with_("kept", f"SELECT level, cx, cy, n FROM kept WHERE {IN_BOX} AND n >= 2 ORDER BY n DESC, level, cx, cy LIMIT 5"))
def restyle_topk(spark, d):
    return query.restyle(viewport_nodes(spark, d), 2, 5)


@query_(with_("mv", f"SELECT ((sx - {BOX[0]}) * 256) // {BOX[2] - BOX[0]} AS px, ((sy - {BOX[1]}) * 256) // {BOX[3] - BOX[1]} AS py, count(*) AS n FROM mv WHERE sx >= {BOX[0]} AND sx < {BOX[2]} AND sy >= {BOX[1]} AND sy < {BOX[3]} GROUP BY ALL"))
def raster_pixels(spark, d):
    return query.rasterize(movements(spark, d), BOX, 256, 256)


# --- bundling


#: Side in cells of the tiles that are drawn apart, by an edge's source cell: about one viewport.
DRAWN_TILE = 32


def kept_lines(spark, d) -> DataFrame:
    """All kept edges of every level. The id packs level and cells (14 bits each), so no order over all edges is needed."""
    e = build(movements(spark, d)).kept_edges
    key = reduce(lambda a, c: a * 16_384 + F.col(c), ("sx", "sy", "tx", "ty"), F.col("level").cast("long"))
    tile = F.floor(F.col("sx") / DRAWN_TILE) * 16_384 + F.floor(F.col("sy") / DRAWN_TILE)
    return e.select(key.alias("id"), "level", tile.alias("tile"), *[F.col(a).cast("double").alias(b) for a, b in (("sx", "x1"), ("sy", "y1"), ("tx", "x2"), ("ty", "y2"))])


def drawn(b: DataFrame, *by: str) -> DataFrame:
    """Edges and straight ink of every drawing, and whether its bundles need no more ink than that."""
    ink = b.groupBy(*by, "bundle").agg(F.count("*").alias("edges"), F.max("bundle_ink").alias("ink"), F.sum("straight_ink").alias("straight"))
    return ink.groupBy(*by).agg(F.sum("edges").alias("edges"), F.round(F.sum("straight"), 6).alias("straight"), (F.sum("ink") <= F.sum("straight") + 1e-6).alias("no_more_ink"))


STRAIGHT = "count(*) AS edges, round(sum(sqrt(CAST((tx - sx) * (tx - sx) + (ty - sy) * (ty - sy) AS DOUBLE))), 6) AS straight, TRUE AS no_more_ink"


@query_(with_("kedges", f"SELECT CAST(level AS INTEGER) AS level, CAST((sx // {DRAWN_TILE}) * 16384 + sy // {DRAWN_TILE} AS BIGINT) AS tile, {STRAIGHT} FROM kedges GROUP BY ALL"))
def bundles(spark, d):
    """All kept edges bundled tile by tile."""
    return drawn(bundling.bundle(kept_lines(spark, d), by=("level", "tile")), "level", "tile")


@query_(with_("kedges", f"SELECT CAST(level AS INTEGER) AS level, {STRAIGHT} FROM kedges GROUP BY level"))
def bundles_all(spark, d):
    """All kept edges bundled level by level, each level one drawing."""
    return drawn(bundling.bundle(kept_lines(spark, d).drop("tile")), "level")


LINE = "SELECT level, (((CAST(level AS BIGINT) * 16384 + sx) * 16384 + sy) * 16384 + tx) * 16384 + ty AS id, sx, sy, tx, ty FROM kedges"
KNN = with_("kedges", f""", e AS ({LINE}), k AS (SELECT a.id, b.id AS other, (a.sx - b.sx) * (a.sx - b.sx) + (a.sy - b.sy) * (a.sy - b.sy) + (a.tx - b.tx) * (a.tx - b.tx) + (a.ty - b.ty) * (a.ty - b.ty) AS d2
    FROM e a JOIN e b ON a.level = b.level AND a.id <> b.id) SELECT id, CAST(r AS INTEGER) AS rank, other FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY d2, other) AS r FROM k) WHERE r <= 5""".lstrip())


def _knn(method: str):
    def knn(spark, d):
        """The five nearest kept edges of every kept edge, level by level, as 4-D points of their ends in cells."""
        p = kept_lines(spark, d).select("id", "level", F.array("x1", "y1", "x2", "y2").alias("p"))
        return bundling.proximity_graph(p, 5, method, by=("level",)).select("id", "rank", "other")

    return knn


query_(KNN, "edge_knn")(_knn("buckets"))
query_(KNN, "edge_knn_naive")(_knn("all_pairs"))


@query_(with_("kedges", "SELECT CAST(level AS INTEGER) AS level, round(sum(sqrt(CAST((tx - sx) * (tx - sx) + (ty - sy) * (ty - sy) AS DOUBLE))), 6) AS ink FROM kedges GROUP BY level"))
def ink_unbundled(spark, d):
    e = build(movements(spark, d)).kept_edges
    dx, dy = F.col("tx") - F.col("sx"), F.col("ty") - F.col("sy")
    return e.groupBy("level").agg(F.round(F.sum(F.sqrt((dx * dx + dy * dy).cast("double"))), 6).alias("ink"))


# --- scans, filters, joins


@query_("SELECT event_id, user_id FROM events WHERE event_type = 'view' AND value > 10")
def scan_events(spark, d):
    return table(spark, d, "events").where("event_type = 'view' and value > 10").select("event_id", "user_id")


@query_(with_("pts", f"SELECT point_id FROM pts WHERE x_mas >= {BOX[0]} AND x_mas < {BOX[2]} AND y_mas >= {BOX[1]} AND y_mas < {BOX[3]}"))
def bbox_filter(spark, d):
    return carriers.points(spark, d).where(geo.in_box(F.col("x_mas"), F.col("y_mas"), *BOX)).select("point_id")


@query_(with_("pts", "SELECT count(*) AS inside FROM pts WHERE x_mas >= 0 AND x_mas < 399360000 AND y_mas >= 0 AND y_mas < 276480000"))
def region_clip(spark, d):
    return geo.clip(carriers.points(spark, d)).agg(F.count("*").alias("inside"))


@query_(with_("wide", "SELECT cx, cy, count(*) AS n FROM wide WHERE level = 8 AND t0 >= TIMESTAMP '2024-01-10' AND t0 < TIMESTAMP '2024-01-20' GROUP BY ALL"))
def level_period_filter(spark, d):
    days = aggregate.pyramid_nodes(movements(spark, d), time_bin="day").where("level = 8 and bin >= timestamp_ntz'2024-01-10' and bin < timestamp_ntz'2024-01-20'")
    return days.groupBy("cx", "cy").agg(F.sum("n").alias("n"))


@query_("SELECT event_id FROM events WHERE event_type IN ('view', 'click') AND props LIKE '%1%'")
def filter_event_type(spark, d):
    return table(spark, d, "events").where(F.col("event_type").isin("view", "click") & F.col("props").like("%1%")).select("event_id")


@query_(with_("ships", "SELECT s_nationkey, c_mktsegment, count(*) AS n, round(sum(l_extendedprice), 2) AS revenue FROM ships GROUP BY ALL"))
def join_shipments(spark, d):
    return carriers.shipments(spark, d).groupBy("s_nationkey", "c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("revenue"))


PROBE = "SELECT point_id * 10 AS probe_id, user_id, ts + INTERVAL 6 HOUR AS asked FROM pts WHERE point_id % 7 = 0"


@query_(with_("pts", f", probes AS ({PROBE}) SELECT probe_id, p.user_id, asked, q.point_id, q.x_mas, q.y_mas FROM probes p ASOF LEFT JOIN pts q ON p.user_id = q.user_id AND p.asked >= q.ts"))
def position_asof(spark, d):
    p = carriers.points(spark, d)
    probes = p.where("point_id % 7 = 0").select((F.col("point_id") * 10).alias("probe_id"), "user_id", (F.col("ts") + F.expr("interval 6 hours")).alias("at"))
    return trajectory.position_at(p, probes).withColumnRenamed("at", "asked")


PROBE_ALL = "SELECT point_id * 10 AS probe_id, user_id, ts + INTERVAL 6 HOUR AS asked FROM pts"


@query_(with_("pts", f", probes AS ({PROBE_ALL}) SELECT probe_id, p.user_id, asked, q.point_id, q.x_mas, q.y_mas FROM probes p ASOF LEFT JOIN pts q ON p.user_id = q.user_id AND p.asked >= q.ts"))
def position_asof_all(spark, d):
    """One probe from every point."""
    p = carriers.points(spark, d)
    probes = p.select((F.col("point_id") * 10).alias("probe_id"), "user_id", (F.col("ts") + F.expr("interval 6 hours")).alias("at"))
    return trajectory.position_at(p, probes).withColumnRenamed("at", "asked")


@query_(with_("mv", "SELECT bin, count(*) AS n FROM (SELECT unnest(range(epoch_us(t0) // 1000000 // 86400, epoch_us(t1) // 1000000 // 86400 + 1)) AS bin FROM mv) GROUP BY bin"))
def movements_alive(spark, d):
    return trajectory.alive_in(movements(spark, d))


@query_(with_("wide", """SELECT level, cx, cy, coalesce(a.n, 0) AS n0, coalesce(b.n, 0) AS n1, coalesce(b.n, 0) - coalesce(a.n, 0) AS delta FROM (SELECT level, cx, cy, count(*) AS n FROM wide WHERE t0 < TIMESTAMP '2024-01-16' GROUP BY ALL) a
    FULL JOIN (SELECT level, cx, cy, count(*) AS n FROM wide WHERE t0 >= TIMESTAMP '2024-01-16' GROUP BY ALL) b USING (level, cx, cy)"""))
def period_change(spark, d):
    mv = movements(spark, d)
    half = F.lit("2024-01-16").cast("timestamp_ntz")
    return query.change(aggregate.pyramid_nodes(mv.where(F.col("t0") < half)), aggregate.pyramid_nodes(mv.where(F.col("t0") >= half)))


NATION = "SELECT n_nationkey, n_name, r_name, (((7 * n_nationkey + 3) % 26) * 15360000 + ((5381 * n_nationkey) % 15360) * 1000) // 15360000 AS cx, (((11 * n_nationkey + 5) % 18) * 15360000 + ((7919 * n_nationkey) % 15360) * 1000) // 15360000 AS cy FROM nation JOIN region ON n_regionkey = r_regionkey"


@query_(with_("nodes", f", homes AS (SELECT cx, cy, min(n_name) AS n_name, min_by(r_name, n_name) AS r_name FROM ({NATION}) GROUP BY cx, cy) SELECT cx, cy, n, n_name, r_name FROM (SELECT * FROM nodes WHERE level = 10) LEFT JOIN homes USING (cx, cy)"))
def nodes_enriched(spark, d):
    x, y = carriers.anchor_xy(F.col("n_nationkey"))
    nation = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    homes = nation.select("n_name", "r_name", grid.cell(x, 10).alias("cx"), grid.cell(y, 10).alias("cy")).groupBy("cx", "cy").agg(F.min("n_name").alias("n_name"), F.min_by("r_name", "n_name").alias("r_name"))
    return nodes(spark, d).where("level = 10").select("cx", "cy", "n").join(homes, ["cx", "cy"], "left")


@query_(with_("kedges", "SELECT level, sx, sy, tx, ty, n, CAST(r AS INTEGER) AS r FROM (SELECT *, row_number() OVER (PARTITION BY level, sx, sy ORDER BY n DESC, tx, ty) AS r FROM kedges) WHERE r <= 3"))
def top_destinations(spark, d):
    w = Window.partitionBy("level", "sx", "sy").orderBy(F.desc("n"), "tx", "ty")
    return build(movements(spark, d)).kept_edges.withColumn("r", F.row_number().over(w)).where("r <= 3").select("level", "sx", "sy", "tx", "ty", "n", "r")


# --- aggregation, windows, top-k, sets, scalars


@query_(with_("nodes", "SELECT level, arg_max(cx, (n, -cx, -cy)) AS cx, arg_max(cy, (n, -cx, -cy)) AS cy, max(n) AS n FROM nodes GROUP BY level"))
def busiest_cell(spark, d):
    m = F.max(F.struct("n", (-F.col("cx")).alias("a"), (-F.col("cy")).alias("b")))
    return nodes(spark, d).groupBy("level").agg(m.alias("m")).select("level", (-F.col("m.a")).alias("cx"), (-F.col("m.b")).alias("cy"), F.col("m.n").alias("n"))


@query_(with_("mv", "SELECT event_type, round(quantile_cont(dist_km, 0.5), 6) AS p50, round(quantile_cont(dist_km, 0.9), 6) AS p90 FROM mv GROUP BY event_type"))
def distance_percentiles(spark, d):
    return movements(spark, d).groupBy("event_type").agg(F.round(F.percentile("dist_km", 0.5), 6).alias("p50"), F.round(F.percentile("dist_km", 0.9), 6).alias("p90"))


DAYS = "SELECT date_trunc('day', t0)::TIMESTAMP AS day, event_type, hour(t0) AS hour, dist_km FROM mv"


@query_(with_("mv", f"SELECT day, event_type, count(*) AS n, round(sum(dist_km), 3) AS km, CAST(grouping(day, event_type) AS INTEGER) AS gid FROM ({DAYS}) GROUP BY CUBE (day, event_type)"))
def cube_measures(spark, d):
    return cube.measure_cube(movements(spark, d))


@query_(with_("mv", f"SELECT event_type, day, count(*) AS n, round(sum(dist_km), 3) AS km, CAST(grouping(event_type, day) AS INTEGER) AS gid FROM ({DAYS}) GROUP BY ROLLUP (event_type, day)"))
def rollup_measures(spark, d):
    return cube.measure_cube(movements(spark, d), "rollup")


@query_(with_("mv", f"SELECT day, event_type, CAST(coalesce(hour, -1) AS INTEGER) AS hour, count(*) AS n, round(sum(dist_km), 3) AS km FROM ({DAYS}) GROUP BY GROUPING SETS ((day), (event_type), (hour, event_type))"))
def grouping_sets_measures(spark, d):
    return cube.measure_cube(movements(spark, d), "sets").withColumn("hour", F.coalesce("hour", F.lit(-1)))


@query_(with_("wide", "SELECT cx, cy, count(*) FILTER (e.event_type = 'view') AS view, count(*) FILTER (e.event_type = 'click') AS click, count(*) FILTER (e.event_type NOT IN ('view', 'click')) AS other FROM wide JOIN events e ON e.event_id = movement_id WHERE level = 9 GROUP BY cx, cy"))
def pivot_event_types(spark, d):
    kind = F.when(F.col("event_type").isin("view", "click"), F.col("event_type")).otherwise("other")
    ends = aggregate.endpoints(movements(spark, d).withColumn("kind", kind), ("kind",))
    return ends.groupBy(grid.cell(F.col("x"), 9).alias("cx"), grid.cell(F.col("y"), 9).alias("cy")).pivot("kind", ["view", "click", "other"]).agg(F.sum(F.lit(1).cast("long"))).na.fill(0)


@query_(with_("wide", "SELECT cx, cy, string_agg(event_type || '=' || c, ',' ORDER BY event_type) AS histogram FROM (SELECT cx, cy, e.event_type, count(*) AS c FROM wide JOIN events e ON e.event_id = movement_id WHERE level = 9 GROUP BY ALL) GROUP BY cx, cy"))
def type_histogram(spark, d):
    ends = aggregate.endpoints(movements(spark, d), ("event_type",))
    c = ends.groupBy(grid.cell(F.col("x"), 9).alias("cx"), grid.cell(F.col("y"), 9).alias("cy"), "event_type").agg(F.count("*").alias("c"))
    held = c.groupBy("cx", "cy").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("event_type", "c")))).alias("m"))
    return held.select("cx", "cy", F.array_join(F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("histogram"))


@query_(with_("ships", "SELECT a.n_name AS s_nation, b.n_name AS c_nation, count(*) AS n, round(sum(l_extendedprice), 2) AS revenue FROM ships JOIN nation a ON s_nationkey = a.n_nationkey JOIN nation b ON c_nationkey = b.n_nationkey GROUP BY ALL"))
def od_matrix_nation(spark, d):
    per = carriers.shipments(spark, d).groupBy("s_nationkey", "c_nationkey").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("revenue"))
    name = lambda k, a: table(spark, d, "nation").select(F.col("n_nationkey").alias(k), F.col("n_name").alias(a))
    return per.join(name("s_nationkey", "s_nation"), "s_nationkey").join(name("c_nationkey", "c_nation"), "c_nationkey").select("s_nation", "c_nation", "n", "revenue")


@query_(with_("ships", "SELECT a.n_regionkey AS s_region, b.n_regionkey AS c_region, count(*) AS n FROM ships JOIN nation a ON s_nationkey = a.n_nationkey JOIN nation b ON c_nationkey = b.n_nationkey GROUP BY ALL"))
def od_matrix_region(spark, d):
    per = carriers.shipments(spark, d).groupBy("s_nationkey", "c_nationkey").agg(F.count("*").alias("n"))
    key = lambda k, a: table(spark, d, "nation").select(F.col("n_nationkey").alias(k), F.col("n_regionkey").alias(a))
    return per.join(key("s_nationkey", "s_region"), "s_nationkey").join(key("c_nationkey", "c_region"), "c_nationkey").groupBy("s_region", "c_region").agg(F.sum("n").alias("n"))


@query_(with_("nodes", "SELECT level, cx, cy, n, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM nodes WINDOW w AS (PARTITION BY level ORDER BY n)"))
def global_ranks(spark, d):
    at = positions(held_nodes(spark, d))
    share = F.when(F.col("nodes") > 1, F.col("before") / (F.col("nodes") - 1)).otherwise(F.lit(0.0))
    return at.select("level", "cx", "cy", "n", (F.col("before") + 1).alias("r"), F.col("value").alias("dr"), F.round(share, 6).alias("pr"), F.round((F.col("before") + F.col("c")) / F.col("nodes"), 6).alias("cd"))


@query_(with_("nodes", "SELECT level, cx, cy, CAST(ntile(5) OVER (PARTITION BY level ORDER BY n, cx, cy) AS INTEGER) AS class FROM nodes"))
def count_classes(spark, d):
    """Five classes of like size; the first ones are larger by one where the nodes do not divide."""
    q, r, i = F.floor(F.col("nodes") / 5), F.col("nodes") % 5, F.col("place") - 1
    wide = r * (q + 1)
    tile = F.when(i < wide, F.floor(i / (q + 1))).otherwise(r + F.floor((i - wide) / q)) + 1
    return positions(held_nodes(spark, d)).select("level", "cx", "cy", tile.cast("int").alias("class"))


@query_(with_("pts", "SELECT point_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, point_id ROWS UNBOUNDED PRECEDING) AS posts FROM pts"))
def running_posts(spark, d):
    return carriers.points(spark, d).select("point_id", F.count("*").over(trajectory.by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("posts"))


@query_(with_("mv", "SELECT movement_id, round(avg(dist_km) OVER (PARTITION BY user_id ORDER BY t0, movement_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 5) AS mean_km FROM mv"))
def moving_distance(spark, d):
    w = Window.partitionBy("user_id").orderBy("t0", "movement_id").rowsBetween(-3, 0)
    return movements(spark, d).select("movement_id", F.round(F.avg("dist_km").over(w), 5).alias("mean_km"))


@query_(with_("pts", "SELECT point_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS posts FROM pts"))
def trailing_day_posts(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-86_400, 0)
    return carriers.points(spark, d).select("point_id", F.count("*").over(w).alias("posts"))


TRIPS = "SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, point_id ROWS UNBOUNDED PRECEDING) AS trip FROM (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, point_id) > 43200 * 1000000::BIGINT THEN 1 ELSE 0 END AS new FROM pts)"


@query_(with_("pts", f"SELECT user_id, CAST(trip AS BIGINT) AS trip, count(*) AS points, min(ts) AS t0, max(ts) AS t1 FROM ({TRIPS}) GROUP BY ALL"))
def trip_sessions(spark, d):
    return trajectory.sessions(carriers.points(spark, d), 43_200).groupBy("user_id", "trip").agg(F.count("*").alias("points"), F.min("ts").alias("t0"), F.max("ts").alias("t1"))


@query_(with_("pts", f"SELECT user_id, CAST(trip AS BIGINT) AS trip, arg_min(x_mas, (ts, point_id)) AS from_x, arg_max(x_mas, (ts, point_id)) AS to_x FROM ({TRIPS}) GROUP BY ALL"))
def trip_endpoints(spark, d):
    w = Window.partitionBy("user_id", "trip").orderBy("ts", "point_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = trajectory.sessions(carriers.points(spark, d), 43_200)
    return t.select("user_id", "trip", F.first("x_mas").over(w).alias("from_x"), F.last("x_mas").over(w).alias("to_x")).distinct()


@query_(with_("nodes", "SELECT level, cx, cy, round(sum(n) OVER (PARTITION BY level ORDER BY n DESC, cx, cy ROWS UNBOUNDED PRECEDING) / sum(n) OVER (PARTITION BY level), 6) AS share FROM nodes"))
def activity_share(spark, d):
    at = positions(held_nodes(spark, d), descending=True)
    reached = F.col("mass") + (F.col("place") - F.col("before")) * F.col("n")
    return at.select("level", "cx", "cy", F.round(reached / F.col("total"), 6).alias("share"))


query_(with_("nodes", "SELECT level, cx, cy, n FROM nodes ORDER BY n DESC, level, cx, cy LIMIT 20"), "top_nodes")(lambda s, d: nodes(s, d).select("level", "cx", "cy", "n").orderBy(F.desc("n"), "level", "cx", "cy").limit(20))
query_(with_("edges", "SELECT level, sx, sy, tx, ty, n FROM edges ORDER BY n DESC, level, sx, sy, tx, ty LIMIT 20"), "top_edges")(lambda s, d: edges(s, d).orderBy(F.desc("n"), "level", "sx", "sy", "tx", "ty").limit(20))
query_(with_("nodes", "SELECT level, cx, cy, n FROM nodes ORDER BY n DESC, level, cx, cy LIMIT 20 OFFSET 40"), "nodes_page")(lambda s, d: nodes(s, d).select("level", "cx", "cy", "n").orderBy(F.desc("n"), "level", "cx", "cy").offset(40).limit(20))


@query_(with_("nodes", "SELECT level, cx, cy, n FROM (SELECT *, row_number() OVER (PARTITION BY level ORDER BY n DESC, cx, cy) AS r FROM nodes) WHERE r <= 5"))
def top_nodes_per_level(spark, d):
    w = Window.partitionBy("level").orderBy(F.desc("n"), "cx", "cy")
    return nodes(spark, d).withColumn("r", F.row_number().over(w)).where("r <= 5").select("level", "cx", "cy", "n")


query_(with_("ends", "SELECT x, y, count(*) AS n FROM ends GROUP BY x, y"), "endpoints_union")(lambda s, d: movements(s, d).select(F.col("sx").alias("x"), F.col("sy").alias("y")).unionByName(movements(s, d).select(F.col("tx").alias("x"), F.col("ty").alias("y"))).groupBy("x", "y").agg(F.count("*").alias("n")))
query_(with_("pts", "SELECT DISTINCT x_mas // 30000 AS cx, y_mas // 30000 AS cy FROM pts"), "distinct_cells")(lambda s, d: carriers.points(s, d).select(grid.cell(F.col("x_mas"), 1).alias("cx"), grid.cell(F.col("y_mas"), 1).alias("cy")).distinct())

_HALF = "(SELECT DISTINCT level, cx, cy FROM wide WHERE t0 {} TIMESTAMP '2024-01-16')"


def _halves(spark, d) -> tuple[DataFrame, DataFrame]:
    mv, half = movements(spark, d), F.lit("2024-01-16").cast("timestamp_ntz")
    return tuple(aggregate.pyramid_nodes(mv.where(c)).select("level", "cx", "cy") for c in (F.col("t0") < half, F.col("t0") >= half))


query_(with_("wide", f"FROM {_HALF.format('<')} INTERSECT FROM {_HALF.format('>=')}"), "persistent_places")(lambda s, d: (lambda a, b: a.intersect(b))(*_halves(s, d)))
query_(with_("wide", f"FROM {_HALF.format('>=')} EXCEPT FROM {_HALF.format('<')}"), "new_places")(lambda s, d: (lambda a, b: b.subtract(a))(*_halves(s, d)))


@query_(with_("mv", "SELECT movement_id, round(CASE WHEN b < 0 THEN b + 360 ELSE b END, 5) AS bearing FROM (SELECT movement_id, degrees(atan2(sin(dl) * cos(b2), cos(b1) * sin(b2) - sin(b1) * cos(b2) * cos(dl))) AS b FROM (SELECT movement_id, radians(7 + sy / 3.6e6) AS b1, radians(7 + ty / 3.6e6) AS b2, radians(-168 + tx / 3.6e6) - radians(-168 + sx / 3.6e6) AS dl FROM mv))"))
def movement_bearing(spark, d):
    return movements(spark, d).select("movement_id", F.round(geo.bearing(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty")), 5).alias("bearing"))


@query_(with_("mv", "SELECT movement_id, round(dist_km * 3600.0 / nullif(travel_s, 0), 5) AS kmh FROM mv"))
def movement_speed(spark, d):
    return movements(spark, d).select("movement_id", F.round(geo.speed_kmh(F.col("dist_km"), F.col("travel_s")), 5).alias("kmh"))


@query_(with_("mv", "SELECT movement_id, travel_s, CAST(hour(t0) AS INTEGER) AS hour, CAST(date_diff('day', t0, t1) AS INTEGER) AS days FROM mv"))
def movement_durations(spark, d):
    return movements(spark, d).select("movement_id", "travel_s", F.hour("t0").alias("hour"), F.datediff("t1", "t0").alias("days"))


@query_(with_("mv", "SELECT CAST(hour(t0) AS INTEGER) AS hour, count(*) AS n FROM mv GROUP BY ALL"))
def hourly_profile(spark, d):
    return movements(spark, d).groupBy(F.hour("t0").alias("hour")).agg(F.count("*").alias("n"))


@query_(with_("nodes", "SELECT 'L' || lpad(CAST(level AS VARCHAR), 2, '0') || '/' || cx || '/' || cy AS label, n FROM nodes"))
def cell_labels(spark, d):
    return nodes(spark, d).select(F.concat(F.lit("L"), F.lpad(F.col("level").cast("string"), 2, "0"), F.lit("/"), F.col("cx").cast("string"), F.lit("/"), F.col("cy").cast("string")).alias("label"), "n")


@query_("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n, round(sum(value), 2) AS value FROM events GROUP BY 1")
def props_metric(spark, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, d, "events").groupBy(k.alias("k")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("value"))


@query_(with_("mv", "SELECT movement_id, 'LINESTRING(' || sx || ' ' || sy || ', ' || tx || ' ' || ty || ')' AS wkt FROM mv"))
def wkt_lines(spark, d):
    return movements(spark, d).select("movement_id", geo.wkt_line(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty")).alias("wkt"))


@query_(with_("kept", "SELECT level, cx, cy, n FROM kept"))
def geojson_features(spark, d):
    """Features written as JSON and parsed back."""
    from ..sources.sinks import feature

    lines = kept(spark, d).select(feature(F.col("cx"), F.col("cy"), F.struct("level", "cx", "cy", "n")).alias("json"))
    back = F.from_json("json", "type string, properties struct<level:int,cx:long,cy:long,n:long>")
    return lines.select(back.alias("f")).select("f.properties.*")


@query_(with_("kept", f"SELECT level, cx, cy, n FROM kept WHERE {IN_BOX}"))
def sql_viewport(spark, d):
    from ..sources.sql import register_views

    g = build(movements(spark, d))
    register_views(spark, g, "sv")
    return spark.sql(f"SELECT level, cx, cy, n FROM sv_kept_nodes WHERE {IN_BOX}")


def ten_batches(spark, d, compact_after: int | None = None) -> str:
    """Path of a cube refreshed with ten batches of movements, one after the other."""
    from ..streaming import streams

    path, mv = fresh_path(spark, "cubes"), materialize(movements(spark, d))
    put = streams.refresh(path)
    for i in range(10):
        put(mv.where(F.col("movement_id") % 10 == i), i)
        if i == compact_after:
            streams.compact(spark, path)
    return path


@query_(with_("wide", "SELECT date_trunc('day', t0)::TIMESTAMP AS bin, level, cx, cy, count(*) AS n FROM wide GROUP BY ALL"))
def incremental_equals_batch(spark, d):
    """The cube's nodes refreshed batch by batch, which must equal those made at once."""
    from ..streaming import streams

    return streams.refreshed(spark, ten_batches(spark, d)).select("bin", "level", "cx", "cy", "n")


@query_(with_("flows", "SELECT date_trunc('day', t0)::TIMESTAMP AS bin, level, sx, sy, tx, ty, count(*) AS n FROM flows WHERE dist_km < cap GROUP BY ALL"))
def incremental_edges(spark, d):
    """The cube's edges after ten batches and a compaction in between."""
    from ..streaming import streams

    return streams.refreshed(spark, ten_batches(spark, d, 6), "edges").select("bin", "level", "sx", "sy", "tx", "ty", "n")


@query_(with_("kedges", "SELECT level, sx, sy, tx, ty, CAST(n AS BIGINT) AS n FROM kedges"))
def incremental_graph(spark, d):
    """The summarized graph after ten batches: kept nodes ranked again only near changed cells, edges filtered by them."""
    from ..operators import bloom
    from ..streaming import streams

    path = ten_batches(spark, d, 4)
    found = streams.refreshed(spark, path, "edges").groupBy("level", "sx", "sy", "tx", "ty").agg(F.sum("n").alias("n"))
    return bloom.join_filter_edges(found, streams.kept_nodes(spark, path))


@query_(with_("kept", "SELECT level, cx, cy, n FROM kept"))
def incremental_nodes(spark, d):
    """The kept nodes after ten batches."""
    from ..streaming import streams

    return streams.kept_nodes(spark, ten_batches(spark, d, 4))


@query_()
def latency_summary(spark, d):
    """Average, median and 90th percentile of the response time in ms of all 3 sets of 2000 viewports of both patterns at the three
    published rates, from the stored cube."""
    from . import workload

    rows = [(r["pattern"], r["seconds"], *(float(r["stored"][k]) for k in ("average", "median", "p90")), r["sets"] * workload.QUERIES_A_SET) for r in workload.stress(spark, d)]
    return spark.createDataFrame(rows, "pattern string, seconds int, average double, median double, p90 double, queries int")
