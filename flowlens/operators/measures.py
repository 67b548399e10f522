"""Measures merged with the graph: a registry of aggregate columns over the movements that touch a cell or run along an edge."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions.grid import by_level, cell

REGISTRY: dict[str, Callable[[], Column]] = {}


def register(name: str, build: Callable[[], Column]) -> None:
    """Make a measure known. It may use user_id, t0, t1, travel_s, dist_km and whatever else the movements have."""
    REGISTRY[name] = build


register("n", lambda: F.count("*"))
register("users", lambda: F.countDistinct("user_id"))
register("users_approx", lambda: F.hll_sketch_estimate(F.hll_sketch_agg("user_id")))
register("avg_travel_s", lambda: F.round(F.avg("travel_s"), 6))
register("avg_km", lambda: F.round(F.avg("dist_km"), 6))
register("min_ts", lambda: F.min("t0"))
register("max_ts", lambda: F.max("t1"))

DEFAULT = ("n", "users", "avg_travel_s", "avg_km", "min_ts", "max_ts")


def node_measures(movements: DataFrame, cfg: PyramidConfig = PyramidConfig(), names: tuple[str, ...] = DEFAULT) -> DataFrame:
    ends = movements.select("user_id", "t0", "t1", "travel_s", "dist_km", F.inline(F.array(F.struct(F.col("sx").alias("x"), F.col("sy").alias("y")), F.struct(F.col("tx").alias("x"), F.col("ty").alias("y")))))
    wide = ends.withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(cfg.grid.levels))))
    keys = [F.col("level"), cell(F.col("x"), F.col("level"), cfg.grid).alias("cx"), cell(F.col("y"), F.col("level"), cfg.grid).alias("cy")]
    return wide.groupBy(*keys).agg(*[REGISTRY[m]().alias(m) for m in names])


def edge_measures(movements: DataFrame, cfg: PyramidConfig = PyramidConfig(), names: tuple[str, ...] = DEFAULT) -> DataFrame:
    wide = movements.withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(cfg.grid.levels)))).where(F.col("dist_km") < by_level(cfg.caps, F.col("level")))
    keys = [F.col("level"), *[cell(F.col(c), F.col("level"), cfg.grid).alias(c) for c in ("sx", "sy", "tx", "ty")]]
    return wide.groupBy(*keys).agg(*[REGISTRY[m]().alias(m) for m in names])
