"""Answering viewports: sub-graphs by rectangle, level and period, drill-down, look-ups, batches, and the baselines without a cube."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import GridSpec, PyramidConfig
from ..functions.grid import cell, morton
from .aggregate import pyramid_edges, pyramid_nodes
from .cube import Cube

BATCH_TILE = 32


def cell_range(lo: int, hi: int, level: int, grid: GridSpec = GridSpec()) -> tuple[int, int]:
    """First and last cell that a half-open interval of coordinates meets."""
    c = grid.cell_mas(level)
    return lo // c, max(lo // c, -(-hi // c) - 1)


def morton_interval(cx0: int, cy0: int, cx1: int, cy1: int) -> tuple[int, int]:
    """Keys between which all cells of a box lie: those of its lower and upper corner."""
    key = lambda x, y: sum(((x >> i) & 1) << 2 * i | ((y >> i) & 1) << 2 * i + 1 for i in range(14))
    return key(cx0, cy0), key(cx1, cy1)


def viewport_nodes(nodes: DataFrame, box: tuple[int, int, int, int], level: int, period: tuple[str, str] | None = None, grid: GridSpec = GridSpec()) -> DataFrame:
    """Nodes of a level whose cells the box meets. With a period (half-open, bin labels) the bins in it are merged into one graph."""
    (cx0, cx1), (cy0, cy1) = cell_range(box[0], box[2], level, grid), cell_range(box[1], box[3], level, grid)
    out = nodes.where(F.col("level") == level)
    if "morton" in nodes.columns:
        lo, hi = morton_interval(cx0, cy0, cx1, cy1)
        out = out.where(F.col("morton").between(lo, hi))
    out = out.where(F.col("cx").between(cx0, cx1) & F.col("cy").between(cy0, cy1))
    if period:
        out = out.where((F.col("bin") >= period[0]) & (F.col("bin") < period[1])).groupBy("level", "cx", "cy").agg(F.sum("n").alias("n"))
    return out


def viewport_edges(edges: DataFrame, visible: DataFrame, level: int, rule: str = "both", period: tuple[str, str] | None = None) -> DataFrame:
    """Edges with both ends, either, or the source or target among the visible nodes."""
    e = edges.where(F.col("level") == level)
    if period:
        e = e.where((F.col("bin") >= period[0]) & (F.col("bin") < period[1])).groupBy("level", "sx", "sy", "tx", "ty").agg(F.sum("n").alias("n"))
    at = lambda x, y: visible.select("level", F.col("cx").alias(x), F.col("cy").alias(y)).distinct()
    source, target = at("sx", "sy"), at("tx", "ty")
    if rule == "either":
        flagged = e.join(source.withColumn("s", F.lit(1)), ["level", "sx", "sy"], "left").join(target.withColumn("t", F.lit(1)), ["level", "tx", "ty"], "left")
        return flagged.where("s = 1 or t = 1").select(*e.columns)
    if rule in ("both", "source"):
        e = e.join(source, ["level", "sx", "sy"], "left_semi")
    if rule in ("both", "target"):
        e = e.join(target, ["level", "tx", "ty"], "left_semi")
    return e


def viewport(cube: Cube, box, level: int, period=None, rule: str = "both") -> tuple[DataFrame, DataFrame]:
    nodes = viewport_nodes(cube.nodes, box, level, period)
    return nodes, viewport_edges(cube.edges, nodes, level, rule, period)


def viewport_raw(movements: DataFrame, box, level: int, cfg: PyramidConfig = PyramidConfig()) -> tuple[DataFrame, DataFrame]:
    """The same answer from raw movements, without anything computed before."""
    one = movements.select("*")
    nodes = viewport_nodes(pyramid_nodes(one, cfg).where(F.col("level") == level), box, level)
    return nodes, viewport_edges(pyramid_edges(one, cfg), nodes, level)


def viewports(nodes: DataFrame, views: DataFrame, grid: GridSpec = GridSpec()) -> DataFrame:
    """A batch of viewports in one job: boxes and nodes meet in tiles of cells, then the exact box decides."""
    size = F.call_function("shiftleft", F.lit(grid.base_mas).cast("long"), F.col("level") - 1)
    last = lambda c: F.greatest(F.ceil(F.col(c) / size) - 1, F.lit(0))
    v = views.select("set_id", "query_id", "level", F.floor(F.col("x0") / size).alias("cx0"), F.floor(F.col("y0") / size).alias("cy0"), last("x1").alias("cx1"), last("y1").alias("cy1"))
    tile = lambda c: F.floor(F.col(c) / BATCH_TILE)
    v = v.withColumn("tx", F.explode(F.sequence(tile("cx0"), tile("cx1")))).withColumn("ty", F.explode(F.sequence(tile("cy0"), tile("cy1"))))
    n = nodes.withColumns({"tx": tile("cx"), "ty": tile("cy")})
    return n.join(v, ["level", "tx", "ty"]).where("cx between cx0 and cx1 and cy between cy0 and cy1").select("set_id", "query_id", "level", "cx", "cy", "n")


def level_for(box, max_cells: int = 1000, grid: GridSpec = GridSpec()) -> int:
    """The finest level at which the box has no more cells than asked."""
    for level in range(1, grid.levels + 1):
        (a, b), (c, d) = cell_range(box[0], box[2], level, grid), cell_range(box[1], box[3], level, grid)
        if (b - a + 1) * (d - c + 1) <= max_cells:
            return level
    return grid.levels


def level_of(x0: Column, y0: Column, x1: Column, y1: Column, max_cells: Column, grid: GridSpec = GridSpec()) -> Column:
    """level_for() of a box in every row."""
    side = lambda lo, hi, level: cell(F.greatest(hi - 1, lo), level, grid) - cell(lo, level, grid) + 1
    fits = [F.when(side(x0, x1, lv) * side(y0, y1, lv) <= max_cells, lv) for lv in range(1, grid.levels + 1)]
    return F.coalesce(*fits, F.lit(grid.levels))


def drill(nodes: DataFrame, level: int, cx: int, cy: int) -> DataFrame:
    """The cells one level finer inside a cell."""
    return nodes.where((F.col("level") == level - 1) & (F.shiftright("cx", 1) == cx) & (F.shiftright("cy", 1) == cy))


def members(movements: DataFrame, edge: tuple[int, int, int, int, int], cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """The movements behind an edge (level, sx, sy, tx, ty)."""
    level, sx, sy, tx, ty = edge
    at = lambda c: cell(F.col(c), level, cfg.grid)
    return movements.where((at("sx") == sx) & (at("sy") == sy) & (at("tx") == tx) & (at("ty") == ty) & (F.col("dist_km") < cfg.caps[level - 1]))


def restyle(result: DataFrame, min_count: int = 1, top_k: int | None = None) -> DataFrame:
    """A returned graph filtered again on its own attributes."""
    out = result.where(F.col("n") >= min_count)
    return out.orderBy(F.desc("n"), *[c for c in result.columns if c != "n"]).limit(top_k) if top_k else out


def rasterize(movements: DataFrame, box, width: int, height: int) -> DataFrame:
    """Pixel counts of movement sources: what a picture keeps, without ids to look up."""
    x0, y0, x1, y1 = box
    inside = movements.where((F.col("sx") >= x0) & (F.col("sx") < x1) & (F.col("sy") >= y0) & (F.col("sy") < y1))
    px = F.call_function("div", (F.col("sx") - x0) * width, F.lit(x1 - x0).cast("long"))
    py = F.call_function("div", (F.col("sy") - y0) * height, F.lit(y1 - y0).cast("long"))
    return inside.groupBy(px.alias("px"), py.alias("py")).agg(F.count("*").alias("n"))


def change(a: DataFrame, b: DataFrame) -> DataFrame:
    """Counts of two periods side by side and their difference; cells of only one period count 0 in the other."""
    k = ["level", "cx", "cy"]
    both = a.select(*k, F.col("n").alias("n0")).join(b.select(*k, F.col("n").alias("n1")), k, "full_outer")
    return both.select(*k, F.coalesce("n0", F.lit(0)).alias("n0"), F.coalesce("n1", F.lit(0)).alias("n1")).withColumn("delta", F.col("n1") - F.col("n0"))


def with_morton(nodes: DataFrame) -> DataFrame:
    return nodes.withColumn("morton", morton(F.col("cx"), F.col("cy")))


def parent(level: int, cx: int, cy: int) -> tuple[int, int, int]:
    """The cell one level coarser that holds a cell."""
    return level + 1, cx >> 1, cy >> 1


def explain_node(nodes: DataFrame, level: int, cx: int, cy: int) -> DataFrame:
    """All attributes that the graph holds of one cell."""
    return nodes.where((F.col("level") == level) & (F.col("cx") == cx) & (F.col("cy") == cy))
