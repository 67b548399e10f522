"""Streams of points: event time, windowed node counts, stateful linking, de-duplication and an incremental cube."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import PyramidConfig
from ..functions.grid import cell
from ..operators.aggregate import pyramid_edges, pyramid_nodes
from ..operators.summarize import rescored
from ..sources.shared import materialize, remove
from ..sources.tables import POINTS_SCHEMA

LINKED = "movement_id long, user_id long, t0 timestamp, t1 timestamp, sx long, sy long, tx long, ty long"
STATE = "ts array<long>, point_id array<long>, x array<long>, y array<long>"


def points_stream(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    """Points from Parquet files as they arrive."""
    return spark.readStream.schema(POINTS_SCHEMA).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def with_event_time(points: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Points whose ts is event time; rows later than the delay are dropped by the operators that follow."""
    return points.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def dedupe(points: DataFrame) -> DataFrame:
    return points.dropDuplicatesWithinWatermark(["point_id"])


def window_nodes(points: DataFrame, size: str, slide: str | None = None, gap: str | None = None, level: int = 6, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """Points per cell of a level in tumbling or sliding windows, or in sessions that a gap ends."""
    span = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    keys = [cell(F.col("x_mas"), level, cfg.grid).alias("cx"), cell(F.col("y_mas"), level, cfg.grid).alias("cy")]
    return points.groupBy(span.alias("w"), *keys).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "cx", "cy", "n")


def _link(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Hold a user's points until the watermark has passed them, then emit movements in time order; the last passed point stays."""
    rows = list(zip(*state.get)) if state.exists else []
    for f in frames:
        at = f["ts"].astype("datetime64[us]").astype("int64")
        rows += list(zip(at.tolist(), f["point_id"].tolist(), f["x_mas"].tolist(), f["y_mas"].tolist()))
    rows = sorted(set(rows))
    mark = state.getCurrentWatermarkMs() * 1000
    ripe = [r for r in rows if r[0] <= mark]
    if rows[max(0, len(ripe) - 1) :]:
        state.update(tuple(list(c) for c in zip(*rows[max(0, len(ripe) - 1) :])))
    later = [r[0] for r in rows if r[0] > mark]
    if later:
        state.setTimeoutTimestamp(min(later) // 1000 + 1)
    out = [(a[1], key[0], a[0], b[0], a[2], a[3], b[2], b[3]) for a, b in zip(ripe, ripe[1:])]
    pdf = pd.DataFrame(out, columns=["movement_id", "user_id", "t0", "t1", "sx", "sy", "tx", "ty"])
    for c in ("t0", "t1"):
        pdf[c] = pd.to_datetime(pdf[c], unit="us")
    yield pdf


def link(points: DataFrame) -> DataFrame:
    """Movements of a point stream with a watermark. State per user: its points since the watermark and one before."""
    cols = points.select("user_id", "ts", "point_id", "x_mas", "y_mas")
    return cols.groupBy("user_id").applyInPandasWithState(_link, LINKED, STATE, "append", "EventTimeTimeout")


def enrich(points: DataFrame, users: DataFrame) -> DataFrame:
    """Stream-static join: points with what is known of their users."""
    return points.join(users, "user_id", "left")


def meetings(points: DataFrame, others: DataFrame, minutes: int = 10, level: int = 6, cfg: PyramidConfig = PyramidConfig()) -> DataFrame:
    """Stream-stream interval join: pairs of points of different users in one cell within so many minutes. Both sides need a watermark;
    the cell is the join key and the interval lets Spark forget old points."""
    at = lambda p, a: p.select(*[F.col(c).alias(f"{a}_{c}") for c in ("point_id", "user_id", "ts")], cell(F.col("x_mas"), level, cfg.grid).alias(f"{a}_cx"), cell(F.col("y_mas"), level, cfg.grid).alias(f"{a}_cy"))
    near = F.expr(f"a_cx = b_cx and a_cy = b_cy and a_user_id < b_user_id and b_ts >= a_ts - interval {minutes} minutes and b_ts <= a_ts + interval {minutes} minutes")
    return at(points, "a").join(at(others, "b"), near)


def late_rows(query) -> int:
    """Rows that a running or finished query has dropped because they came after the watermark, over the progress it still holds."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in json.loads(p.json if hasattr(p, "json") else json.dumps(p))["stateOperators"])


NODES = "level int, cx long, cy long, bin timestamp_ntz, n long, sum_x long, sum_y long"
EDGES = "level int, sx long, sy long, tx long, ty long, bin timestamp_ntz, n long"
KEPT = "level int, cx long, cy long, n long"


def refresh(path: str, cfg: PyramidConfig = PyramidConfig(), summarize_too: bool = True):
    """foreachBatch sink for movements: node and edge counts of each batch go to folders named by the batch, so a repeated batch replaces
    itself. With summarize_too the kept nodes follow: only places near a cell that the batch touched are ranked again."""

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        pyramid_nodes(batch, cfg, time_bin="day").write.mode("overwrite").parquet(f"{path}/nodes/batch={batch_id}")
        pyramid_edges(batch, cfg, time_bin="day").write.mode("overwrite").parquet(f"{path}/edges/batch={batch_id}")
        if summarize_too:
            changed = spark.read.schema(NODES).parquet(f"{path}/nodes/batch={batch_id}").select("level", "cx", "cy").distinct()
            nodes = materialize(refreshed(spark, path).groupBy("level", "cx", "cy").agg(F.sum("n").alias("n")))
            before = kept_nodes(spark, path, batch_id)
            rescored(nodes, changed, before, cfg).write.mode("overwrite").parquet(f"{path}/kept/version={batch_id}")

    return put


def _folders(spark: SparkSession, path: str) -> list[int]:
    """Numbers of the folders name=number under a path."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = at.getFileSystem(spark._jsc.hadoopConfiguration())
    names = [s.getPath().getName() for s in files.listStatus(at)] if files.exists(at) else []
    return sorted(int(n.split("=")[1]) for n in names if "=" in n)


def refreshed(spark: SparkSession, path: str, kind: str = "nodes") -> DataFrame:
    """Nodes or edges of the cube from all batches so far: counts and sums add up."""
    schema, keys = (NODES, ["level", "cx", "cy", "bin"]) if kind == "nodes" else (EDGES, ["level", "sx", "sy", "tx", "ty", "bin"])
    rows = spark.read.schema(schema + ", batch long").parquet(f"{path}/{kind}")
    return rows.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in rows.columns if c not in (*keys, "batch")])


def kept_nodes(spark: SparkSession, path: str, before: int | None = None) -> DataFrame:
    """The kept nodes after the last batch, or after the last one before a given batch."""
    have = [v for v in _folders(spark, f"{path}/kept") if before is None or v < before]
    return spark.read.schema(KEPT).parquet(f"{path}/kept/version={have[-1]}") if have else spark.createDataFrame([], KEPT)


def compact(spark: SparkSession, path: str) -> None:
    """Merge all batch folders into the last one's and drop older versions of the kept nodes, so that reads do not slow down with the
    number of batches. To be called between batches."""
    for kind in ("nodes", "edges"):
        have = _folders(spark, f"{path}/{kind}")
        if len(have) > 1:
            refreshed(spark, path, kind).write.mode("overwrite").parquet(f"{path}/merged_{kind}")
            for b in have:
                remove(spark, f"{path}/{kind}/batch={b}")
            at = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/merged_{kind}")
            at.getFileSystem(spark._jsc.hadoopConfiguration()).rename(at, spark._jvm.org.apache.hadoop.fs.Path(f"{path}/{kind}/batch={have[-1]}"))
    for v in _folders(spark, f"{path}/kept")[:-1]:
        remove(spark, f"{path}/kept/version={v}")
