"""Helpers shared by the training-data operators: reading, shared tables, checked broadcasts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import shared
from ..sources.shared import discard, scratch  # noqa: F401

#: Rows above which a lookup table is no longer broadcast but joined by key.
BROADCAST_ROWS = 100_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows that pass between the JVM and a Python worker at a time while materialize() runs, which bounds both sides' buffers.
ARROW_ROWS = "2000"


def materialize(df: DataFrame, lasting: bool = False) -> DataFrame:
    """A table in the shared folder (see sources.shared): inside scratch() it goes with the block, a lasting one with the block around it."""
    spark = df.sparkSession
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(setting)
    spark.conf.set(setting, ARROW_ROWS)
    try:
        return shared.materialize(df, lasting)
    finally:
        spark.conf.set(setting, before)


def join_lookup(df: DataFrame, lookup: DataFrame, on, how: str = "left") -> DataFrame:
    """Join with a lookup table: broadcast only when its counted rows stay below BROADCAST_ROWS, else by key with AQE skew splitting."""
    small = lookup.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    return df.join(F.broadcast(lookup) if small else lookup, on, how)


def n_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def slices(batches, rows: int = 512):
    """Arrow batches in smaller pieces, which bounds what a kernel holds as Python objects at a time."""
    for b in batches:
        for k in range(0, b.num_rows, rows):
            yield b.slice(k, rows)
