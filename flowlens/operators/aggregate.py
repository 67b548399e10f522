"""The pyramid: node and edge counts for every level, in several interchangeable strategies."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions.grid import by_level, cell

NODE = ["level", "cx", "cy"]
EDGE = ["level", "sx", "sy", "tx", "ty"]


def _levels(cfg: PyramidConfig) -> Column:
    return F.explode(F.sequence(F.lit(1), F.lit(cfg.grid.levels)))


def _up(c: str) -> Column:
    return F.call_function("shiftright", F.col(c), F.col("level") - 1)


def endpoints(movements: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """(x, y) of both ends of every movement, in one scan."""
    return movements.select(*keep, F.inline(F.array(F.struct(F.col("sx").alias("x"), F.col("sy").alias("y")), F.struct(F.col("tx").alias("x"), F.col("ty").alias("y")))))


def pyramid_nodes(movements: DataFrame, cfg: PyramidConfig = PyramidConfig(), strategy: str | None = None, time_bin: str | None = None) -> DataFrame:
    """level, cx, cy (, bin), n, sum_x, sum_y: one increment at either end of every movement at every level.

    rollup: counts the finest cells first and sums those upwards, so that the fan-out over levels works on cells, not movements.
    explode: every movement at every level, merged before the shuffle. none: the same without that merge. in_task: tables per task,
    flushed when large, then merged. builtin: key-value reduction over rows.
    """
    strategy = strategy or cfg.aggregation
    keys = NODE + (["bin"] if time_bin else [])
    keep = ("bin",) if time_bin else ()
    if time_bin:
        movements = movements.withColumn("bin", F.date_trunc(time_bin, F.col("t0").cast("timestamp_ntz")))
    ends = endpoints(movements, keep)
    sums = [F.sum("n").alias("n"), F.sum("sum_x").alias("sum_x"), F.sum("sum_y").alias("sum_y")]
    count = [F.count("*").alias("n"), F.sum("x").alias("sum_x"), F.sum("y").alias("sum_y")]
    g = cfg.grid
    if strategy == "rollup":
        fine = ends.groupBy(cell(F.col("x"), 1, g).alias("fx"), cell(F.col("y"), 1, g).alias("fy"), *keep).agg(*count)
        return fine.withColumn("level", _levels(cfg)).groupBy("level", _up("fx").alias("cx"), _up("fy").alias("cy"), *keep).agg(*sums)
    wide = ends.withColumn("level", _levels(cfg))
    wide = wide.select("level", cell(F.col("x"), F.col("level"), g).alias("cx"), cell(F.col("y"), F.col("level"), g).alias("cy"), "x", "y", *keep)
    if strategy == "explode":
        return wide.groupBy(*keys).agg(*count)
    if strategy == "none":
        return wide.repartition(*keys).groupBy(*keys).agg(*count)
    if strategy == "in_task":
        return wide.select(*NODE, "x", "y").mapInArrow(task_tables(), "level int, cx long, cy long, n long, sum_x long, sum_y long").groupBy(*NODE).agg(*sums)
    if strategy == "builtin":
        pairs = wide.select(*NODE, "x", "y").rdd.map(lambda r: ((r[0], r[1], r[2]), (1, r[3], r[4])))
        merged = pairs.reduceByKey(lambda a, b: (a[0] + b[0], a[1] + b[1], a[2] + b[2])).map(lambda kv: (*kv[0], *kv[1]))
        return wide.sparkSession.createDataFrame(merged, "level int, cx long, cy long, n long, sum_x long, sum_y long")
    raise ValueError(f"unknown strategy {strategy}")


def task_tables(most_rows: int = 1 << 20):
    """Kernel that merges all increments of a task before it emits any; the table is flushed when it has most_rows."""

    def run(batches):
        held: list[pa.Table] = []
        rows = 0

        def merged(tables: list[pa.Table]) -> pa.Table:
            t = pa.concat_tables(tables).group_by(NODE).aggregate([("n", "sum"), ("sum_x", "sum"), ("sum_y", "sum")])
            return t.select(NODE + ["n_sum", "sum_x_sum", "sum_y_sum"]).rename_columns(NODE + ["n", "sum_x", "sum_y"])

        for b in batches:
            t = pa.Table.from_batches([b]).group_by(NODE).aggregate([([], "count_all"), ("x", "sum"), ("y", "sum")])
            held.append(t.select(NODE + ["count_all", "x_sum", "y_sum"]).rename_columns(NODE + ["n", "sum_x", "sum_y"]))
            rows += t.num_rows
            if rows > most_rows:
                held = [merged(held)]
                rows = held[0].num_rows
                if rows > most_rows // 2:
                    yield from held[0].to_batches()
                    held, rows = [], 0
        if held:
            yield from merged(held).to_batches()

    return run


def first_level(dist: Column, cfg: PyramidConfig) -> Column:
    """The finest level whose cap admits a movement of this length; null if none does. Caps never fall, so all coarser ones do too."""
    out = F.lit(None).cast("int")
    for level in range(cfg.grid.levels, 0, -1):
        out = F.when(dist < F.lit(cfg.caps[level - 1]), F.lit(level)).otherwise(out)
    return out


def pyramid_edges(movements: DataFrame, cfg: PyramidConfig = PyramidConfig(), strategy: str | None = None, directed: bool = True, loops: bool = True, time_bin: str | None = None) -> DataFrame:
    """level, sx, sy, tx, ty (, bin), n: movements shorter than the level's cap between each pair of cells.

    The roll-up keeps the first admitting level in its finest key, so that capped counts still add up exactly.
    """
    strategy = strategy or cfg.aggregation
    keep = ["bin"] if time_bin else []
    if time_bin:
        movements = movements.withColumn("bin", F.date_trunc(time_bin, F.col("t0").cast("timestamp_ntz")))
    g = cfg.grid
    if strategy == "rollup":
        fine = movements.select(*[cell(F.col(c), 1, g).alias(c) for c in ("sx", "sy", "tx", "ty")], first_level(F.col("dist_km"), cfg).alias("lo"), *keep)
        fine = fine.where("lo is not null").groupBy("sx", "sy", "tx", "ty", "lo", *keep).agg(F.count("*").alias("m"))
        wide = fine.withColumn("level", F.explode(F.sequence("lo", F.lit(g.levels)))).select("level", *[_up(c).alias(c) for c in ("sx", "sy", "tx", "ty")], "m", *keep)
    else:
        wide = movements.withColumn("level", _levels(cfg)).where(F.col("dist_km") < by_level(cfg.caps, F.col("level")))
        wide = wide.select("level", *[cell(F.col(c), F.col("level"), g).alias(c) for c in ("sx", "sy", "tx", "ty")], F.lit(1).cast("long").alias("m"), *keep)
    if not directed:
        a, b = F.least(F.struct("sx", "sy"), F.struct(F.col("tx").alias("sx"), F.col("ty").alias("sy"))), F.greatest(F.struct("sx", "sy"), F.struct(F.col("tx").alias("sx"), F.col("ty").alias("sy")))
        wide = wide.select("level", a["sx"].alias("sx"), a["sy"].alias("sy"), b["sx"].alias("tx"), b["sy"].alias("ty"), "m", *keep)
    if not loops:
        wide = wide.where("sx <> tx or sy <> ty")
    return wide.groupBy(*EDGE, *keep).agg(F.sum("m").alias("n"))


def fine_flows(movements: DataFrame, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """Movements merged by their finest cells and first admitting level: what nodes and edges of every level can be summed from, so
    that both come from one scan. m: movements; x0, y0, x1, y1: sums of their ends' coordinates."""
    g = cfg.grid
    cells = [cell(F.col(c), 1, g).alias(f"f{c}") for c in ("sx", "sy", "tx", "ty")]
    sums = [F.sum(c).alias(a) for c, a in (("sx", "x0"), ("sy", "y0"), ("tx", "x1"), ("ty", "y1"))]
    return movements.groupBy(*cells, first_level(F.col("dist_km"), cfg).alias("lo")).agg(F.count("*").alias("m"), *sums)


def nodes_of_flows(flows: DataFrame, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """pyramid_nodes() from fine_flows()."""
    end = lambda x, y, sx, sy: F.struct(F.col(x).alias("fx"), F.col(y).alias("fy"), F.col(sx).alias("x"), F.col(sy).alias("y"))
    ends = flows.select("m", F.inline(F.array(end("fsx", "fsy", "x0", "y0"), end("ftx", "fty", "x1", "y1"))))
    fine = ends.groupBy("fx", "fy").agg(F.sum("m").alias("n"), F.sum("x").alias("sum_x"), F.sum("y").alias("sum_y"))
    return fine.withColumn("level", _levels(cfg)).groupBy("level", _up("fx").alias("cx"), _up("fy").alias("cy")).agg(*[F.sum(c).alias(c) for c in ("n", "sum_x", "sum_y")])


def edges_of_flows(flows: DataFrame, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """pyramid_edges() from fine_flows()."""
    wide = flows.where("lo is not null").withColumn("level", F.explode(F.sequence("lo", F.lit(cfg.grid.levels))))
    return wide.select("level", *[_up(f"f{c}").alias(c) for c in ("sx", "sy", "tx", "ty")], "m").groupBy(*EDGE).agg(F.sum("m").alias("n"))


def centroids(nodes: DataFrame) -> DataFrame:
    """Mean position of what was counted in each cell, by whole-number division."""
    return nodes.select(*NODE, F.call_function("div", F.col("sum_x"), F.col("n")).alias("cent_x"), F.call_function("div", F.col("sum_y"), F.col("n")).alias("cent_y"))


def point_nodes(points: DataFrame, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """The pyramid of single positions: every point counts once, where endpoints count inner points twice."""
    fine = points.groupBy(cell(F.col("x_mas"), 1, cfg.grid).alias("fx"), cell(F.col("y_mas"), 1, cfg.grid).alias("fy")).agg(F.count("*").alias("n"), F.sum("x_mas").alias("sum_x"), F.sum("y_mas").alias("sum_y"))
    return fine.withColumn("level", _levels(cfg)).groupBy("level", _up("fx").alias("cx"), _up("fy").alias("cy")).agg(F.sum("n").alias("n"), F.sum("sum_x").alias("sum_x"), F.sum("sum_y").alias("sum_y"))


def adjacency(edges: DataFrame) -> DataFrame:
    """Nodes with their targets nested, as a map from packed cell id to count."""
    from ..functions.grid import cell_id

    return edges.groupBy("level", F.col("sx").alias("cx"), F.col("sy").alias("cy")).agg(F.map_from_entries(F.collect_list(F.struct(cell_id(F.col("tx"), F.col("ty")), F.col("n")))).alias("targets"))


def degrees(edges: DataFrame) -> DataFrame:
    """Outgoing, incoming and all movements of each cell, and its distinct neighbours."""
    out = edges.select("level", F.col("sx").alias("cx"), F.col("sy").alias("cy"), F.struct("tx", "ty").alias("o"), F.col("n").alias("n_out"), F.lit(0).cast("long").alias("n_in"))
    into = edges.select("level", F.col("tx").alias("cx"), F.col("ty").alias("cy"), F.struct(F.col("sx").alias("tx"), F.col("sy").alias("ty")).alias("o"), F.lit(0).cast("long").alias("n_out"), F.col("n").alias("n_in"))
    return out.unionByName(into).groupBy(*NODE).agg(F.sum("n_out").alias("n_out"), F.sum("n_in").alias("n_in"), F.countDistinct("o").alias("neighbours"))
