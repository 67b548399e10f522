"""The space-time cube: the graph of every time bin stored partitioned by level and bin, clustered along the Morton curve."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import morton


@dataclass
class Cube:
    nodes: DataFrame
    edges: DataFrame


def _write(df: DataFrame, path: str, x: str, y: str) -> None:
    laid = df.withColumn("morton", morton(F.col(x), F.col(y)))
    # the shuffle's own sizing decides how many tasks write: as many as are set, fewer where adaptive execution finds them small
    laid = laid.repartitionByRange("level", "morton").sortWithinPartitions("level", "bin", "morton")
    laid.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("level", "bin").parquet(path)


def write(nodes: DataFrame, edges: DataFrame, path: str) -> None:
    """Store nodes and edges that carry a bin (a date or 'all'). Rewriting touches only the bins that the frames hold."""
    _write(nodes.withColumn("bin", F.col("bin").cast("string")), f"{path}/nodes", "cx", "cy")
    _write(edges.withColumn("bin", F.col("bin").cast("string")), f"{path}/edges", "sx", "sy")


def open_cube(spark: SparkSession, path: str) -> Cube:
    read = lambda kind: spark.read.option("basePath", f"{path}/{kind}").parquet(f"{path}/{kind}").withColumn("bin", F.col("bin").cast("string"))
    return Cube(read("nodes"), read("edges"))


def save_bucketed(edges: DataFrame, name: str, buckets: int = 16) -> None:
    """Edges as a catalog table bucketed by source cell, so that joins on it need no shuffle of the edges."""
    edges.write.mode("overwrite").bucketBy(buckets, "level", "sx", "sy").sortBy("level", "sx", "sy").saveAsTable(name)


def measure_cube(movements: DataFrame, by: str = "cube") -> DataFrame:
    """Movements by level-10 hour of day, day and type over all, nested or chosen subsets of the dimensions."""
    base = movements.select(F.date_trunc("day", F.col("t0").cast("timestamp_ntz")).alias("day"), "event_type", F.hour("t0").alias("hour"), "dist_km")
    agg = [F.count("*").alias("n"), F.round(F.sum("dist_km"), 3).alias("km")]
    if by == "cube":
        return base.cube("day", "event_type").agg(*agg, F.grouping_id().cast("int").alias("gid"))
    if by == "rollup":
        return base.rollup("event_type", "day").agg(*agg, F.grouping_id().cast("int").alias("gid"))
    return base.groupingSets([["day"], ["event_type"], ["hour", "event_type"]], "day", "event_type", "hour").agg(*agg)
