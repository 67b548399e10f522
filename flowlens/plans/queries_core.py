"""Queries over the pyramid: movements, nodes, edges, significance, Bloom filters and their baselines."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions import grid
from ..operators import aggregate, bloom, measures, partitioning, summarize, trajectory
from ..sources import carriers
from ..sources.shared import materialize
from .oracle_sql import with_
from .pipeline import build

QUERIES, ORACLES = {}, {}
CFG = PyramidConfig()


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


def movements(spark: SparkSession, d: str) -> DataFrame:
    return trajectory.build_movements(carriers.points(spark, d))


def nodes(spark: SparkSession, d: str, strategy: str = "rollup") -> DataFrame:
    return aggregate.pyramid_nodes(movements(spark, d), CFG, strategy)


def edges(spark: SparkSession, d: str, **how) -> DataFrame:
    return aggregate.pyramid_edges(movements(spark, d), CFG, **how)


def held_nodes(spark: SparkSession, d: str) -> DataFrame:
    """The nodes as a stored table, for queries that read them several times."""
    return materialize(nodes(spark, d))


def kept(spark: SparkSession, d: str) -> DataFrame:
    return summarize.significant_nodes(held_nodes(spark, d), CFG)


def r6(c: str):
    return F.round(F.col(c), 6).alias(c)


MV = "SELECT movement_id, user_id, t0, t1, sx, sy, tx, ty, round(dist_km, 6) AS dist_km FROM mv"


@query(with_("mv", MV))
def movements_from_events(spark, d):
    return movements(spark, d).select("movement_id", "user_id", "t0", "t1", "sx", "sy", "tx", "ty", r6("dist_km"))


@query(with_("mv", MV + " WHERE travel_s <= 86400 AND dist_km >= 1 AND (sx // 30000 <> tx // 30000 OR sy // 30000 <> ty // 30000)"))
def movements_gap_filtered(spark, d):
    mv = trajectory.build_movements(carriers.points(spark, d), max_gap_s=86_400, min_displacement_km=1.0, drop_same_cell=1)
    return mv.select("movement_id", "user_id", "t0", "t1", "sx", "sy", "tx", "ty", r6("dist_km"))


@query(with_("pts", "SELECT user_id, count(*) AS points, min(ts) AS first_ts, max(ts) AS last_ts, arg_min(x_mas, (ts, point_id)) AS first_x, arg_max(x_mas, (ts, point_id)) AS last_x FROM pts GROUP BY user_id"))
def trajectory_arrays(spark, d):
    a = trajectory.as_arrays(carriers.points(spark, d))
    first, last = F.col("path")[0], F.element_at("path", -1)
    return a.select("user_id", F.size("path").cast("long").alias("points"), first["ts"].alias("first_ts"), last["ts"].alias("last_ts"), first["x_mas"].alias("first_x"), last["x_mas"].alias("last_x"))


@query(with_("ships", "SELECT user_id, t0, t1, sx, sy, tx, ty FROM ships"))
def movements_from_shipments(spark, d):
    return carriers.shipments(spark, d).select("user_id", "t0", "t1", "sx", "sy", "tx", "ty")


@query(with_("pts lv", "SELECT point_id, level, (x_mas // 30000) >> (level - 1) AS cx, (y_mas // 30000) >> (level - 1) AS cy FROM pts, lv"))
def cell_assignment(spark, d):
    p = carriers.points(spark, d).withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(10))))
    return p.select("point_id", "level", grid.cell(F.col("x_mas"), F.col("level")).alias("cx"), grid.cell(F.col("y_mas"), F.col("level")).alias("cy"))


@query(with_("pts lv", """, used AS (SELECT level, (x_mas // 30000) >> (level - 1) AS cx, (y_mas // 30000) >> (level - 1) AS cy, count(*) AS n FROM pts, lv GROUP BY ALL),
    seen AS (SELECT level, count(*) AS occupied, CAST(sum(n) AS BIGINT) AS points FROM used GROUP BY level) SELECT level, 30000 * (1 << (level - 1))::BIGINT AS cell_mas, (1 << (level - 1))::BIGINT AS nominal_km,
    CAST(ceil(399360000 / (30000 * (1 << (level - 1)))) AS BIGINT) AS cols, CAST(ceil(276480000 / (30000 * (1 << (level - 1)))) AS BIGINT) AS rows,
    CAST(ceil(399360000 / (30000 * (1 << (level - 1)))) * ceil(276480000 / (30000 * (1 << (level - 1)))) AS BIGINT) AS cells,
    CAST(coalesce(occupied, 0) AS BIGINT) AS occupied, CAST(coalesce(points, 0) AS BIGINT) AS points FROM lv LEFT JOIN seen USING (level)"""))
def grid_levels(spark, d):
    """The grids, and how many of their cells the points occupy, counted up from the finest cells."""
    fine = carriers.points(spark, d).groupBy(grid.cell(F.col("x_mas"), 1).alias("fx"), grid.cell(F.col("y_mas"), 1).alias("fy")).agg(F.count("*").alias("m"))
    wide = fine.withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(CFG.grid.levels))))
    up = lambda c: F.call_function("shiftright", F.col(c), F.col("level") - 1)
    seen = wide.groupBy("level", up("fx").alias("cx"), up("fy").alias("cy")).agg(F.sum("m").alias("n")).groupBy("level").agg(F.count("*").alias("occupied"), F.sum("n").alias("points"))
    zero = F.lit(0).cast("long")
    return grid.level_table(spark).join(seen, "level", "left").withColumns({c: F.coalesce(c, zero) for c in ("occupied", "points")})


def _morton_sql(bits: int = 14) -> str:
    part = lambda c, off: " + ".join(f"(((({c}) >> {i}) & 1) << {2 * i + off})" for i in range(bits))
    return f"{part('cx', 0)} + {part('cy', 1)}"


@query(with_("pts", f"SELECT point_id, CAST({_morton_sql()} AS BIGINT) AS morton FROM (SELECT point_id, x_mas // 30000 AS cx, y_mas // 30000 AS cy FROM pts)"))
def morton_keys(spark, d):
    p = carriers.points(spark, d)
    return p.select("point_id", grid.morton(grid.cell(F.col("x_mas"), 1), grid.cell(F.col("y_mas"), 1)).alias("morton"))


@query(with_("mv", "SELECT movement_id, round(dist_km, 6) AS dist_km FROM mv"))
def movement_distance(spark, d):
    return movements(spark, d).select("movement_id", r6("dist_km"))


NODES = "SELECT level, cx, cy, n, sum_x, sum_y FROM nodes"
for _key, _how in (("pyramid_nodes", "explode"), ("pyramid_nodes_rollup", "rollup"), ("pyramid_nodes_intask", "in_task"), ("combiner_builtin", "builtin"), ("combiner_none", "none")):
    query(with_("nodes", NODES), _key)(lambda spark, d, how=_how: nodes(spark, d, how).select("level", "cx", "cy", "n", "sum_x", "sum_y"))

EDGES = "SELECT level, sx, sy, tx, ty, n FROM edges"
query(with_("edges", EDGES), "pyramid_edges")(lambda spark, d: edges(spark, d, strategy="explode"))
query(with_("edges", EDGES), "pyramid_edges_rollup")(lambda spark, d: edges(spark, d, strategy="rollup"))


@query(with_("flows", "SELECT level, sx, sy, tx, ty, count(*) AS n FROM flows GROUP BY ALL"))
def pyramid_edges_uncapped(spark, d):
    return aggregate.pyramid_edges(movements(spark, d), replace(CFG, uncapped=True))


@query(with_("flows", """SELECT level, least((sx, sy), (tx, ty))[1] AS sx, least((sx, sy), (tx, ty))[2] AS sy, greatest((sx, sy), (tx, ty))[1] AS tx, greatest((sx, sy), (tx, ty))[2] AS ty, count(*) AS n
    FROM flows WHERE dist_km < cap AND (sx <> tx OR sy <> ty) GROUP BY ALL"""))
def pyramid_edges_undirected(spark, d):
    return edges(spark, d, directed=False, loops=False)


@query(with_("nodes", "SELECT level, cx, cy, sum_x // n AS cent_x, sum_y // n AS cent_y FROM nodes"))
def node_centroids(spark, d):
    return aggregate.centroids(nodes(spark, d))


@query(with_("pts lv", "SELECT level, (x_mas // 30000) >> (level - 1) AS cx, (y_mas // 30000) >> (level - 1) AS cy, CAST(sum(x_mas) // count(*) AS BIGINT) AS cent_x, CAST(sum(y_mas) // count(*) AS BIGINT) AS cent_y FROM pts, lv GROUP BY ALL"))
def node_centroids_points(spark, d):
    return aggregate.centroids(aggregate.point_nodes(carriers.points(spark, d)))


MEASURES = "count(*) AS n, count(DISTINCT user_id) AS users, round(avg(travel_s), 6) AS avg_travel_s, round(avg(dist_km), 6) AS avg_km, min(t0) AS min_ts, max(t1) AS max_ts"


@query(with_("wide", f"SELECT level, cx, cy, {MEASURES} FROM wide GROUP BY level, cx, cy"))
def node_measures(spark, d):
    return measures.node_measures(movements(spark, d))


@query(with_("flows", f"SELECT level, sx, sy, tx, ty, {MEASURES} FROM flows WHERE dist_km < cap GROUP BY level, sx, sy, tx, ty"))
def edge_measures(spark, d):
    return measures.edge_measures(movements(spark, d))


@query(with_("wide", "SELECT level, cx, cy, count(DISTINCT user_id) AS users FROM wide GROUP BY level, cx, cy"))
def users_exact(spark, d):
    return measures.node_measures(movements(spark, d), names=("users",))


@query()
def node_users_hll(spark, d):
    return measures.node_measures(movements(spark, d), names=("users_approx",))


@query(with_("wide", "SELECT level, TRUE AS within FROM wide GROUP BY level"))
def hll_error(spark, d):
    """Whether every level's estimates of users stay within 10 % on average of the exact counts."""
    m = measures.node_measures(movements(spark, d), names=("users", "users_approx"))
    return m.groupBy("level").agg((F.avg(F.abs(F.col("users_approx") - F.col("users")) / F.col("users")) < 0.1).alias("within"))


@query(with_("wide", "SELECT date_trunc('day', t0)::TIMESTAMP AS day, level, cx, cy, count(*) AS n FROM wide GROUP BY ALL"))
def cube_nodes_daily(spark, d):
    return aggregate.pyramid_nodes(movements(spark, d), time_bin="day").select(F.col("bin").alias("day"), "level", "cx", "cy", "n")


@query(with_("flows", "SELECT date_trunc('day', t0)::TIMESTAMP AS day, level, sx, sy, tx, ty, count(*) AS n FROM flows WHERE dist_km < cap GROUP BY ALL"))
def cube_edges_daily(spark, d):
    return aggregate.pyramid_edges(movements(spark, d), time_bin="day").select(F.col("bin").alias("day"), "level", "sx", "sy", "tx", "ty", "n")


@query(with_("edges", "SELECT level, sx AS cx, sy AS cy, count(*) AS targets, CAST(sum(n) AS BIGINT) AS n FROM edges GROUP BY ALL"))
def adjacency_lists(spark, d):
    a = aggregate.adjacency(edges(spark, d))
    return a.select("level", "cx", "cy", F.size("targets").cast("long").alias("targets"), F.aggregate(F.map_values("targets"), F.lit(0).cast("long"), lambda x, y: x + y).alias("n"))


@query(with_("edges", """SELECT level, cx, cy, CAST(sum(o) AS BIGINT) AS n_out, CAST(sum(i) AS BIGINT) AS n_in, count(DISTINCT (qx, qy)) AS neighbours FROM (
    SELECT level, sx AS cx, sy AS cy, tx AS qx, ty AS qy, n AS o, 0 AS i FROM edges UNION ALL SELECT level, tx, ty, sx, sy, 0, n FROM edges) GROUP BY level, cx, cy"""))
def node_degrees(spark, d):
    return aggregate.degrees(edges(spark, d))


# --- significance

SCORES = "SELECT level, cx, cy, n, neighbours, round(rank_weak, 6) AS rank_weak, round(rank_strict, 6) AS rank_strict, round(rank_mean, 6) AS rank_mean, round(rank_relative, 6) AS rank_relative FROM scores"


@query(with_("scores", SCORES))
def node_scores(spark, d):
    s = summarize.node_scores(held_nodes(spark, d), CFG)
    return s.select("level", "cx", "cy", "n", "neighbours", *[r6(f"rank_{k}") for k in ("weak", "strict", "mean", "relative")])


KEPT = "SELECT level, cx, cy, n FROM kept"
for _key, _how in (("significant_nodes", "tiles"), ("significant_nodes_tiles", "tiles"), ("significant_nodes_offsets", "offsets")):
    query(with_("kept", KEPT), _key)(lambda spark, d, how=_how: summarize.significant_nodes(held_nodes(spark, d), CFG, how))


def work_sample(spark, d) -> DataFrame:
    """x, y, n, key: cell centres of the nodes of every level that a fifth of the movements give, what they count, and their place in
    order of level and Morton key."""
    part = aggregate.pyramid_nodes(partitioning.sample(movements(spark, d), 0.2), CFG)
    key = F.shiftleft(F.col("level").cast("long"), 28).bitwiseOR(grid.morton(F.col("cx"), F.col("cy")))
    return part.select(grid.centre(F.col("cx"), F.col("level")).alias("x"), grid.centre(F.col("cy"), F.col("level")).alias("y"), "n", key.alias("key"))


def work_tree(spark, d, k: int = 16, axis: str = "best", weight: str | None = None) -> partitioning.PartitionTree:
    """Leaves from a sample of the work, each cell of the sample one unit of it, or weighed by its count."""
    return partitioning.learn(work_sample(spark, d), k, axis=axis, weight=weight)


@query(with_("kept", KEPT))
def significant_nodes_leaves(spark, d):
    return summarize.significant_nodes(held_nodes(spark, d), CFG, "leaves", work_tree(spark, d))


@query(with_("kept", KEPT + " WHERE level >= 4"))
def significant_nodes_naive(spark, d):
    """The all-pairs baseline, on the coarser levels only: it is quadratic in a level's nodes."""
    return summarize.significant_nodes(held_nodes(spark, d).where("level >= 4"), CFG, "all_pairs")


@query()
def significant_nodes_all_pairs(spark, d):
    """The all-pairs baseline over every level. Without SQL: the tiles strategy must give the same rows."""
    return summarize.significant_nodes(held_nodes(spark, d), CFG, "all_pairs")


for _rank in ("strict", "mean", "relative"):
    query(with_("scores", f"SELECT level, cx, cy, n FROM scores WHERE rank_{_rank} > 0.8"), f"significant_nodes_{_rank}")(lambda spark, d, rank=_rank: summarize.significant_nodes(held_nodes(spark, d), replace(CFG, rank=rank)))


def _within(condition: str) -> str:
    return f"SELECT level, cx, cy, n FROM around WHERE {condition} GROUP BY level, cx, cy, n HAVING CAST(count(*) FILTER (qn <= n) AS DOUBLE) / count(*) > 0.8"


@query(with_("around", _within("abs(dx) <= 3 AND abs(dy) <= 3")))
def significant_nodes_box(spark, d):
    return summarize.significant_nodes(held_nodes(spark, d), replace(CFG, metric="grid_box"))


@query(with_("nodes lv", """, off AS (SELECT unnest(range(-4, 5)) AS dy), c AS (SELECT *, radians(-168 + (cx * (30000 << (level - 1)) + (30000 << (level - 1)) // 2) / 3.6e6) AS lon, radians(7 + (cy * (30000 << (level - 1)) + (30000 << (level - 1)) // 2) / 3.6e6) AS lat FROM nodes)
    SELECT p.level, p.cx, p.cy, p.n FROM c p, off, c q WHERE q.level = p.level AND q.cy = p.cy + dy AND abs(q.cx - p.cx) <= 31 AND ((q.cx = p.cx AND dy = 0) OR
      2 * 6371.0088 * asin(sqrt(pow(sin((q.lat - p.lat) / 2), 2) + cos(p.lat) * cos(q.lat) * pow(sin((q.lon - p.lon) / 2), 2))) < 3 * (1 << (p.level - 1)))
    GROUP BY ALL HAVING CAST(count(*) FILTER (q.n <= p.n) AS DOUBLE) / count(*) > 0.8""".lstrip()))
def significant_nodes_geo(spark, d):
    return summarize.significant_nodes(held_nodes(spark, d), replace(CFG, metric="great_circle"))


@query(with_("around", "SELECT CAST(r AS INTEGER) AS radius, level, count(*) AS kept FROM (SELECT r, level, cx, cy, n FROM around, (SELECT unnest([2, 3, 4, 6]) AS r) WHERE dx * dx + dy * dy < r * r GROUP BY ALL HAVING CAST(count(*) FILTER (qn <= n) AS DOUBLE) / count(*) > 0.8) GROUP BY ALL"))
def significant_nodes_radius_sweep(spark, d):
    ns, out = held_nodes(spark, d), None
    for r in (2, 3, 4, 6):
        one = summarize.significant_nodes(ns, replace(CFG, radius_cells=(r,) * 10)).groupBy("level").agg(F.count("*").alias("kept")).select(F.lit(r).alias("radius"), "level", "kept")
        out = one if out is None else out.unionByName(one)
    return out


@query(with_("scores", "SELECT CAST(t AS DOUBLE) AS threshold, level, count(*) AS kept FROM scores, (SELECT unnest([0.5, 0.8, 0.9]) AS t) WHERE rank_weak > t GROUP BY ALL"))
def significant_nodes_threshold_sweep(spark, d):
    s = summarize.node_scores(held_nodes(spark, d), CFG).withColumn("threshold", F.explode(F.array(F.lit(0.5), F.lit(0.8), F.lit(0.9))))
    return s.where("rank_weak > threshold").groupBy("threshold", "level").agg(F.count("*").alias("kept"))


@query(with_("nodes", "SELECT level, cx, cy, n FROM (SELECT *, cume_dist() OVER (PARTITION BY level ORDER BY n) AS r FROM nodes) WHERE r > 0.8"))
def significant_nodes_global(spark, d):
    return summarize.globally_significant(nodes(spark, d))


@query(with_("nodes kept", """SELECT level, CAST(count(*) FILTER (l AND g) AS BIGINT) AS both_kept, CAST(count(*) FILTER (l AND NOT g) AS BIGINT) AS local_only, CAST(count(*) FILTER (g AND NOT l) AS BIGINT) AS global_only FROM (
    SELECT n.level, k.n IS NOT NULL AS l, cume_dist() OVER (PARTITION BY n.level ORDER BY n.n) > 0.8 AS g FROM nodes n LEFT JOIN kept k USING (level, cx, cy)) GROUP BY level"""))
def local_vs_global(spark, d):
    ns = held_nodes(spark, d)
    loc = summarize.significant_nodes(ns, CFG).select("level", "cx", "cy", F.lit(True).alias("l"))
    glo = summarize.globally_significant(ns).select("level", "cx", "cy", F.lit(True).alias("g"))
    both = ns.join(loc, ["level", "cx", "cy"], "left").join(glo, ["level", "cx", "cy"], "left").select("level", F.coalesce("l", F.lit(False)).alias("l"), F.coalesce("g", F.lit(False)).alias("g"))
    return both.groupBy("level").agg(F.count_if(F.col("l") & F.col("g")).alias("both_kept"), F.count_if(F.col("l") & ~F.col("g")).alias("local_only"), F.count_if(F.col("g") & ~F.col("l")).alias("global_only"))


@query(with_("nodes kept", "SELECT level, cx, cy, n FROM nodes WHERE (level, cx, cy) NOT IN (SELECT (level, cx, cy) FROM kept)"))
def dropped_nodes(spark, d):
    ns = held_nodes(spark, d)
    return ns.join(summarize.significant_nodes(ns, CFG), ["level", "cx", "cy"], "left_anti").select("level", "cx", "cy", "n")


# --- edge filters

KEDGES = "SELECT level, sx, sy, tx, ty, n FROM kedges"


@query(with_("kedges", KEDGES))
def final_graph(spark, d):
    """Edges between kept nodes: the filters' output, checked by semi-joins."""
    return build(movements(spark, d)).kept_edges


@query(with_("bedges", "SELECT level, sx, sy, tx, ty, n FROM bedges"))
def final_graph_bloom(spark, d):
    """The three steps with the filters' output as it is."""
    return build(movements(spark, d), replace(CFG, edge_filter="bloom")).kept_edges


for _key, _how in (("edges_join", None), ("edges_join_broadcast", "broadcast"), ("join_sortmerge", "merge"), ("join_shuffled_hash", "shuffle_hash")):
    query(with_("kedges", KEDGES), _key)(lambda spark, d, how=_how: bloom.join_filter_edges(edges(spark, d), kept(spark, d), how))


@query(with_("bedges", "SELECT level, sx, sy, tx, ty, n FROM bedges"))
def edges_bloom(spark, d):
    return bloom.bloom_filter_edges(edges(spark, d), materialize(kept(spark, d)))


@query(with_("bits", "SELECT level, pos FROM bits"))
def bloom_bits(spark, d):
    k = materialize(kept(spark, d))
    return bloom.set_bits(k, bloom.sizes(k))


@query(with_("dimk", "SELECT level, kept, m, k FROM dimk"))
def bloom_sizing(spark, d):
    k = bloom.sizes(kept(spark, d))
    return spark.createDataFrame([(lv, *v) for lv, v in k.items()], "level int, kept long, m long, k int")


@query(with_("probe", "SELECT level, cx, cy FROM probe"))
def bloom_probe(spark, d):
    """Nodes that pass the filter, by counting matched bits in plain SQL operators."""
    ns = held_nodes(spark, d)
    k = materialize(summarize.significant_nodes(ns, CFG))
    dims = bloom.sizes(k)
    table_ = F.broadcast(spark.createDataFrame([(lv, m, h) for lv, (_, m, h) in dims.items()], "level int, m long, k int"))
    each = ns.join(table_, "level").withColumn("i", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    each = each.select("level", "cx", "cy", "k", bloom.position(grid.cell_id(F.col("cx"), F.col("cy")), F.col("i").cast("long"), F.col("m")).alias("pos"))
    hit = each.join(bloom.set_bits(k, dims), ["level", "pos"], "left_semi")
    return hit.groupBy("level", "cx", "cy", "k").agg(F.count("*").alias("c")).where("c = k").select("level", "cx", "cy")


@query(with_("kedges bedges lv", """SELECT level, (SELECT count(*) FROM kedges k WHERE k.level = lv.level) AS exact_edges, (SELECT count(*) FROM bedges b WHERE b.level = lv.level) AS bloom_edges,
    (SELECT count(*) FROM bedges b WHERE b.level = lv.level) - (SELECT count(*) FROM kedges k WHERE k.level = lv.level) AS false_pos, CAST(0 AS BIGINT) AS false_neg FROM lv"""))
def bloom_error(spark, d):
    e, k = materialize(edges(spark, d)), materialize(kept(spark, d))
    exact, passed = materialize(bloom.join_filter_edges(e, k)), materialize(bloom.bloom_filter_edges(e, k))
    tag = lambda df, **flags: df.select("level", *[F.lit(flags.get(c, 0)).cast("long").alias(c) for c in ("exact_edges", "bloom_edges", "false_pos", "false_neg")])
    parts = tag(exact, exact_edges=1).unionByName(tag(passed, bloom_edges=1)).unionByName(tag(passed.exceptAll(exact), false_pos=1)).unionByName(tag(exact.exceptAll(passed), false_neg=1))
    levels = spark.range(1, 11).select(F.col("id").cast("int").alias("level"))
    parts = parts.unionByName(tag(levels))
    return parts.groupBy("level").agg(*[F.sum(c).alias(c) for c in ("exact_edges", "bloom_edges", "false_pos", "false_neg")])


@query(with_("nodes edges", "SELECT 'node' AS kind, level, count(*) AS c, CAST(sum(n) AS BIGINT) AS n FROM nodes GROUP BY level UNION ALL SELECT 'edge', level, count(*), CAST(sum(n) AS BIGINT) FROM edges GROUP BY level"))
def graph_unsummarized(spark, d):
    size = lambda df, kind: df.groupBy("level").agg(F.count("*").alias("c"), F.sum("n").alias("n")).select(F.lit(kind).alias("kind"), "level", "c", "n")
    return size(nodes(spark, d), "node").unionByName(size(edges(spark, d), "edge"))

