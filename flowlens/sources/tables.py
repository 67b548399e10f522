"""Scans of the given tables and of raw point files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

POINTS_SCHEMA = "point_id long, user_id long, ts timestamp_ntz, x_mas long, y_mas long"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def points_csv(spark: SparkSession, path: str, header: bool = True) -> DataFrame:
    """Points from CSV; lines that do not parse keep their text in _bad."""
    return spark.read.schema(POINTS_SCHEMA + ", _bad string").option("header", header).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad").csv(path)


def points_json(spark: SparkSession, path: str) -> DataFrame:
    """Points from JSON lines; lines that do not parse keep their text in _bad."""
    return spark.read.schema(POINTS_SCHEMA + ", _bad string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad").json(path)


def split_bytes(spark: SparkSession, n: int) -> None:
    """Bytes that one scan task reads at most."""
    spark.conf.set("spark.sql.files.maxPartitionBytes", str(n))
