"""Tables in the folder that the driver and all executors share, and when they go."""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_open = threading.local()


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir. Where it is unset, a temporary one in local mode, else an error: no
    executor would see a folder of the driver's machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="flowlens-"))
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


def fresh_path(spark: SparkSession, kind: str = "tables") -> str:
    """A path of this application that holds nothing yet."""
    return f"{shared_dir(spark)}/{kind}/{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def materialize(df: DataFrame, lasting: bool = False) -> DataFrame:
    """Write to a table in the shared folder and read it back, which cuts lineage and survives lost executors. Inside scratch() the
    table goes with the block; a lasting one with the block around it, if there is one."""
    spark, scopes = df.sparkSession, getattr(_open, "scopes", [])
    path = fresh_path(spark)
    at = len(scopes) - (2 if lasting else 1)
    if at >= 0:
        scopes[at].append(path)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.table_path = path
    return out


def discard(df: DataFrame) -> None:
    """Delete the table behind a frame that materialize() returned; other frames are left alone."""
    path = vars(df).get("table_path")
    if path:
        remove(df.sparkSession, path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Delete the tables that materialize() writes in the block when it ends. What the block returns must read lasting ones only."""
    scopes = _open.scopes = getattr(_open, "scopes", [])
    scopes.append([])
    try:
        yield
    finally:
        for path in scopes.pop():
            remove(spark, path)


def drop_tables(spark: SparkSession, kind: str = "tables") -> None:
    """Delete all that this application still holds under shared_dir(), once results that read it are stored."""
    remove(spark, f"{shared_dir(spark)}/{kind}/{spark.sparkContext.applicationId}")
