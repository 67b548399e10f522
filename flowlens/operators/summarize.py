"""Local significance: a node stays if its count ranks high among the nodes around it at the same level."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions.geo import great_circle_km
from ..functions.grid import by_level, centre

KEY = ["level", "cx", "cy"]
#: Side of a tile in cells for the disc and box metrics; at least twice any radius keeps replication at four tiles or fewer.
TILE = 16
#: Kilometres of 30 arc-seconds along a meridian, and cells that a great-circle neighbourhood may reach in longitude at the region's north.
KM_A_CELL = 2 * math.pi * 6371.0088 / 360 / 120


def ranks(le: Column, lt: Column, n: Column) -> dict[str, Column]:
    """Four readings of a percentile rank from counts of neighbours no larger, smaller, and all (itself included)."""
    le, lt, n = le.cast("double"), lt.cast("double"), n.cast("double")
    return {"weak": le / n, "strict": lt / n, "mean": (le + lt) / 2 / n, "relative": F.when(n > 1, lt / F.greatest(n - 1, F.lit(1.0))).otherwise(F.lit(0.0))}


def _reach(cfg: PyramidConfig) -> tuple[int, int]:
    """Rows and columns of cells that a neighbourhood may span to either side."""
    r = max(cfg.radii)
    if cfg.metric != "great_circle":
        return r, r
    north = cfg.grid.region.south + cfg.grid.region.height / 3_600_000
    return math.ceil(r / KM_A_CELL), math.ceil(r / (KM_A_CELL * math.cos(math.radians(min(north, 89.0)))))


def _near(cfg: PyramidConfig, level: str = "level") -> Column:
    """Whether q (qx, qy) lies in the neighbourhood of p (cx, cy)."""
    r = by_level(cfg.radii, F.col(level))
    dx, dy = F.col("qx") - F.col("cx"), F.col("qy") - F.col("cy")
    if cfg.metric == "grid_circle":
        return dx * dx + dy * dy < r * r
    if cfg.metric == "grid_box":
        return (F.abs(dx) <= r) & (F.abs(dy) <= r)
    c = lambda v: centre(F.col(v), F.col(level), cfg.grid)
    km = great_circle_km(c("cx"), c("cy"), c("qx"), c("qy"), cfg.grid.region)
    return ((dx == 0) & (dy == 0)) | (km < r * by_level([float(cfg.grid.nominal_km(i)) for i in range(1, cfg.grid.levels + 1)], F.col(level)))


def _counted(pairs: DataFrame, extra: list[str]) -> DataFrame:
    le, lt, n = F.count_if(F.col("qn") <= F.col("n")), F.count_if(F.col("qn") < F.col("n")), F.count("*")
    return pairs.groupBy(*extra, *KEY, "n").agg(le.alias("le"), lt.alias("lt"), n.alias("neighbours"))


def _tiles(nodes: DataFrame, cfg: PyramidConfig) -> DataFrame:
    """Counts inside tiles: q goes to every tile its reach meets, p only to its own, so one exchange by tile serves join and counting."""
    ry, rx = _reach(cfg)
    side_x, side_y = max(TILE, rx), max(TILE, ry)
    tile = lambda c, side, d=0: F.floor((F.col(c) + d) / side)
    p = nodes.select(*KEY, "n", tile("cx", side_x).alias("tx"), tile("cy", side_y).alias("ty"))
    q = nodes.select("level", F.col("cx").alias("qx"), F.col("cy").alias("qy"), F.col("n").alias("qn"), F.explode(F.sequence(tile("cx", side_x, -rx), tile("cx", side_x, rx))).alias("tx"), F.sequence(tile("cy", side_y, -ry), tile("cy", side_y, ry)).alias("_ys"))
    q = q.select("level", "qx", "qy", "qn", "tx", F.explode("_ys").alias("ty"))
    return _counted(p.join(q, ["level", "tx", "ty"]).where(_near(cfg)), ["tx", "ty"])


def _offsets(nodes: DataFrame, cfg: PyramidConfig) -> DataFrame:
    """Counts by probing every cell of the neighbourhood; the list of offsets is fixed by the radii."""
    spark = nodes.sparkSession
    ry, rx = _reach(cfg)
    disc = [(i + 1, dx, dy) for i, r in enumerate(cfg.radii) for dx in range(-rx, rx + 1) for dy in range(-ry, ry + 1) if cfg.metric == "great_circle" or (dx * dx + dy * dy < r * r if cfg.metric == "grid_circle" else max(abs(dx), abs(dy)) <= r)]
    off = F.broadcast(spark.createDataFrame(disc, "level int, dx long, dy long"))
    p = nodes.join(off, "level").select(*KEY, "n", (F.col("cx") + F.col("dx")).alias("qx"), (F.col("cy") + F.col("dy")).alias("qy"))
    q = nodes.select("level", F.col("cx").alias("qx"), F.col("cy").alias("qy"), F.col("n").alias("qn"))
    pairs = p.join(q, ["level", "qx", "qy"])
    return _counted(pairs.where(_near(cfg)) if cfg.metric == "great_circle" else pairs, [])


def _all_pairs(nodes: DataFrame, cfg: PyramidConfig) -> DataFrame:
    """Every node told to every other of its level: the rejected baseline, for small levels only."""
    q = nodes.select(F.col("level").alias("ql"), F.col("cx").alias("qx"), F.col("cy").alias("qy"), F.col("n").alias("qn"))
    return _counted(nodes.join(q, F.col("level") == F.col("ql")).where(_near(cfg)), [])


def _leaves(nodes: DataFrame, cfg: PyramidConfig, tree) -> DataFrame:
    """Counts inside spatial partitions: nodes are copied to every leaf their box meets, each leaf counts for the nodes it owns."""
    from .partitioning import by_cuts, leaves_within

    ry, rx = _reach(cfg)
    at = nodes.select(*[F.col(c).cast("long").alias(c) for c in (*KEY, "n")]).withColumns({"x": centre(F.col("cx"), F.col("level"), cfg.grid), "y": centre(F.col("cy"), F.col("level"), cfg.grid)})
    at = at.withColumns({"off": F.call_function("shiftleft", F.lit(cfg.grid.base_mas * (max(rx, ry) + 1)).cast("long"), (F.col("level") - 1).cast("int")), "own": by_cuts(tree, F.col("x"), F.col("y"))})
    copies = leaves_within(at, tree, "off").select(*KEY, "n", "own", "leaf")
    radii, metric = cfg.radii, cfg.metric

    def score(group: pa.Table) -> pa.Table:
        lv, cx, cy, n, own, leaf = (group.column(c).to_numpy() for c in (*KEY, "n", "own", "leaf"))
        out = []
        for level in np.unique(lv):
            at = np.flatnonzero(lv == level)
            key = cx[at] << 20 | cy[at]
            at = at[np.argsort(key)]
            key, count = np.sort(key), n[at]
            mine = np.flatnonzero(own[at] == leaf[at])
            r = radii[int(level) - 1]
            le, lt, all_ = (np.zeros(len(mine), np.int64) for _ in range(3))
            for a in range(-r, r + 1):
                for b in range(-r, r + 1):
                    if metric == "grid_box" or a * a + b * b < r * r:
                        x, y = cx[at][mine] + a, cy[at][mine] + b
                        asked = np.where((x < 0) | (y < 0), -1, x << 20 | y)
                        place = np.minimum(np.searchsorted(key, asked), len(key) - 1)
                        there = key[place] == asked
                        all_ += there
                        le += there & (count[place] <= count[mine])
                        lt += there & (count[place] < count[mine])
            out.append(np.stack([lv[at][mine], cx[at][mine], cy[at][mine], count[mine], le, lt, all_], 1))
        cols = np.concatenate(out) if out else np.zeros((0, 7), np.int64)
        return pa.table({name: pa.array(cols[:, i], pa.int64()) for i, name in enumerate((*KEY, "n", "le", "lt", "neighbours"))})

    if metric == "great_circle":
        raise ValueError("the leaf strategy counts by cells; use tiles or offsets for great-circle neighbourhoods")
    done = copies.groupBy("leaf").applyInArrow(score, "level long, cx long, cy long, n long, le long, lt long, neighbours long")
    return done.withColumn("level", F.col("level").cast("int"))


def node_scores(nodes: DataFrame, cfg: PyramidConfig = PyramidConfig(), strategy: str | None = None, tree=None) -> DataFrame:
    """level, cx, cy, n, neighbours and the four ranks. The result is the same for every strategy and partitioning."""
    nodes = nodes.select(*KEY, "n")
    how = strategy or cfg.strategy
    counted = {"tiles": _tiles, "offsets": _offsets, "all_pairs": _all_pairs}.get(how)
    counted = _leaves(nodes, cfg, tree) if how == "leaves" else counted(nodes, cfg)
    r = ranks(F.col("le"), F.col("lt"), F.col("neighbours"))
    return counted.select(*KEY, "n", "neighbours", *[c.alias(f"rank_{k}") for k, c in r.items()])


def rescored(nodes: DataFrame, changed: DataFrame, kept: DataFrame, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """significant_nodes() after the counts of some cells (level, cx, cy) have changed, from the nodes kept before.

    Only nodes whose neighbourhood holds a changed cell are ranked again, and only cells within reach of those are read for it.
    """
    spark, (ry, rx) = nodes.sparkSession, _reach(cfg)
    reach = lambda k: F.broadcast(spark.createDataFrame([(dx, dy) for dx in range(-k * rx, k * rx + 1) for dy in range(-k * ry, k * ry + 1)], "dx long, dy long"))
    around = lambda k: changed.select(*KEY).distinct().crossJoin(reach(k)).select("level", (F.col("cx") + F.col("dx")).alias("cx"), (F.col("cy") + F.col("dy")).alias("cy")).distinct()
    again = around(1)
    near = nodes.join(around(2), KEY, "left_semi")
    fresh = significant_nodes(near, cfg).join(again, KEY, "left_semi")
    return kept.join(again, KEY, "left_anti").select(*KEY, "n").unionByName(fresh)


def positions(nodes: DataFrame, descending: bool = False) -> DataFrame:
    """level, cx, cy, n with: c (nodes of the level with this count), before and mass (nodes, and their counts' sum, that come earlier by
    count), value (place of the count among distinct ones), place (in order of count, cx, cy), and the level's nodes and total.

    Orders come from histograms by count, and by count and column, which the grid bounds, so no level is sorted in one task.
    """
    by_n = Window.partitionBy("level").orderBy(F.desc("n") if descending else F.asc("n"))
    earlier, whole = by_n.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy("level")
    hist = nodes.groupBy("level", "n").agg(F.count("*").alias("c"))
    sum_ = lambda e, w: F.coalesce(F.sum(e).over(w), F.lit(0).cast("long"))
    hist = hist.select("level", "n", "c", sum_("c", earlier).alias("before"), sum_(F.col("c") * F.col("n"), earlier).alias("mass"), F.row_number().over(by_n).cast("long").alias("value"), F.sum("c").over(whole).alias("nodes"), F.sum(F.col("c") * F.col("n")).over(whole).alias("total"))
    ties = nodes.groupBy("level", "n", "cx").agg(F.count("*").alias("_c"))
    ties = ties.select("level", "n", "cx", sum_("_c", Window.partitionBy("level", "n").orderBy("cx").rowsBetween(Window.unboundedPreceding, -1)).alias("_left"))
    row = F.row_number().over(Window.partitionBy("level", "n", "cx").orderBy("cy"))
    out = nodes.select(*KEY, "n", row.alias("_row")).join(ties, ["level", "n", "cx"]).join(hist, ["level", "n"])
    return out.withColumn("place", F.col("before") + F.col("_left") + F.col("_row")).drop("_left", "_row")


def significant_nodes(nodes: DataFrame, cfg: PyramidConfig = PyramidConfig(), strategy: str | None = None, tree=None) -> DataFrame:
    """level, cx, cy, n of the nodes whose rank is above the threshold."""
    return node_scores(nodes, cfg, strategy, tree).where(F.col(f"rank_{cfg.rank}") > cfg.threshold).select(*KEY, "n")


def globally_significant(nodes: DataFrame, threshold: float = 0.8) -> DataFrame:
    """The baseline with one ranking for the whole level: share of its nodes with no larger count.

    Ranks come from a histogram of counts, which has few rows however many nodes a level has, so no level is sorted in one task.
    """
    w = Window.partitionBy("level").orderBy("n").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    hist = nodes.groupBy("level", "n").agg(F.count("*").alias("c"))
    high = hist.withColumn("_r", F.sum("c").over(w) / F.sum("c").over(Window.partitionBy("level"))).where(F.col("_r") > threshold).select("level", "n")
    return nodes.join(high, ["level", "n"], "left_semi").select(*KEY, "n")
