"""Trajectories: linking a user's points into movements, sessions, positions in between."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geo import great_circle_km
from ..functions.grid import cell

def by_user():
    return Window.partitionBy("user_id").orderBy("ts", "point_id")


def seconds(a: str, b: str):
    return (F.unix_micros(F.col(b).cast("timestamp")) - F.unix_micros(F.col(a).cast("timestamp"))) / 1_000_000


def build_movements(points: DataFrame, max_gap_s: int | None = None, min_displacement_km: float | None = None, drop_same_cell: int | None = None) -> DataFrame:
    """Each point linked to the same user's next one. Options drop pairs that are too far apart in time, too close in space, or inside
    one cell of a level. A user with one point has no movement."""
    nxt = {f"_{c}": F.lead(c).over(by_user()) for c in ("ts", "x_mas", "y_mas")}
    mv = points.where("x_mas is not null and y_mas is not null").withColumns(nxt).where("_ts is not null")
    mv = mv.select(F.col("point_id").alias("movement_id"), "user_id", F.col("ts").alias("t0"), F.col("_ts").alias("t1"), F.col("x_mas").alias("sx"), F.col("y_mas").alias("sy"), F.col("_x_mas").alias("tx"), F.col("_y_mas").alias("ty"), *[c for c in ("event_type", "value") if c in points.columns])
    mv = mv.withColumns({"dist_km": great_circle_km(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty")), "travel_s": seconds("t0", "t1").cast("long")})
    if max_gap_s is not None:
        mv = mv.where(F.col("travel_s") <= max_gap_s)
    if min_displacement_km is not None:
        mv = mv.where(F.col("dist_km") >= min_displacement_km)
    if drop_same_cell is not None:
        mv = mv.where((cell(F.col("sx"), drop_same_cell) != cell(F.col("tx"), drop_same_cell)) | (cell(F.col("sy"), drop_same_cell) != cell(F.col("ty"), drop_same_cell)))
    return mv


def as_arrays(points: DataFrame) -> DataFrame:
    """One row a user with all points in order; for users whose points fit a row."""
    return points.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("ts", "point_id", "x_mas", "y_mas"))).alias("path"))


def sessions(points: DataFrame, gap_s: int) -> DataFrame:
    """Points with the number of their trip: a new one starts after a gap of more than gap_s seconds."""
    before = F.lag("ts").over(by_user())
    new = F.coalesce((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(before.cast("timestamp")) > gap_s * 1_000_000).cast("long"), F.lit(0))
    return points.withColumn("_new", new).withColumn("trip", F.sum("_new").over(by_user().rowsBetween(Window.unboundedPreceding, 0))).drop("_new")


def position_at(points: DataFrame, probes: DataFrame) -> DataFrame:
    """As-of join: for every probe (probe_id, user_id, at) the user's last point at or before it, null if none. One sort by user."""
    both = points.select("user_id", F.col("ts").alias("_t"), F.lit(0).alias("_k"), F.col("point_id").alias("_tie"), F.struct("point_id", "x_mas", "y_mas").alias("_p"), F.lit(None).cast("long").alias("probe_id"))
    asked = probes.select("user_id", F.col("at").alias("_t"), F.lit(1).alias("_k"), F.col("probe_id").alias("_tie"), F.lit(None).cast(both.schema["_p"].dataType).alias("_p"), "probe_id")
    w = Window.partitionBy("user_id").orderBy("_t", "_k", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    out = both.unionByName(asked).withColumn("_last", F.last("_p", ignorenulls=True).over(w)).where("_k = 1")
    return out.select("probe_id", "user_id", F.col("_t").alias("at"), "_last.point_id", "_last.x_mas", "_last.y_mas")


def alive_in(movements: DataFrame, hours: int = 24) -> DataFrame:
    """Movements under way in every bin of so many hours: bins are listed per movement, never joined by range."""
    width = hours * 3600
    lo, hi = (F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / width) for c in ("t0", "t1"))
    return movements.select("movement_id", F.explode(F.sequence(lo, hi)).alias("bin")).groupBy("bin").agg(F.count("*").alias("n"))
