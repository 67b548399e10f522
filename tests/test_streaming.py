"""Streams against batch results."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from flowlens.operators import aggregate, summarize
from flowlens.operators.trajectory import build_movements
from flowlens.sources import carriers
from flowlens.streaming import streams

from .conftest import SF


def replay(spark, tmp_path, files=4):
    p = carriers.points(spark, SF).select("point_id", "user_id", "ts", "x_mas", "y_mas")
    last = spark.createDataFrame([(-1, -1, 0, 0)], "point_id long, user_id long, x_mas long, y_mas long").select("point_id", "user_id", F.lit("2024-03-01").cast("timestamp_ntz").alias("ts"), "x_mas", "y_mas")
    path = str(tmp_path / "in")
    day = F.ntile(files).over(Window.orderBy("ts"))
    for i in range(1, files + 1):
        p.withColumn("d", day).where(F.col("d") == i).drop("d").coalesce(1).write.mode("append").parquet(path)
    for k in range(3):  # a late sentinel, so that the watermark passes everything
        last.withColumn("point_id", F.lit(-1 - k).cast("long")).withColumn("ts", F.col("ts") + F.expr(f"interval {k} days")).coalesce(1).write.mode("append").parquet(path)
    return path, p


def test_linking_equals_batch(spark, tmp_path):
    path, p = replay(spark, tmp_path)
    mv = streams.link(streams.with_event_time(streams.points_stream(spark, path), "1 hour"))
    q = mv.writeStream.format("memory").queryName("linked").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    q.stop()
    got = {tuple(r) for r in spark.table("linked").where("user_id >= 0").select("movement_id", "user_id", "sx", "tx").collect()}
    want = {tuple(r) for r in build_movements(p).select("movement_id", "user_id", "sx", "tx").collect()}
    assert got == want


def test_windows_and_duplicates(spark, tmp_path):
    path, p = replay(spark, tmp_path)
    w = streams.window_nodes(streams.dedupe(streams.with_event_time(streams.points_stream(spark, path))), "1 day")
    q = w.writeStream.format("memory").queryName("windows").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    q.stop()
    assert spark.table("windows").where("start < '2024-02-15'").agg(F.sum("n")).first()[0] == p.count()


def collect(frame, name, tmp_path):
    q = frame.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / name)).start()
    q.processAllAvailable()
    q.stop()
    return frame.sparkSession.table(name)


def test_joins_with_tables_and_streams(spark, tmp_path):
    path, p = replay(spark, tmp_path)
    timed = lambda: streams.with_event_time(streams.points_stream(spark, path, 100), "1 hour")
    users = p.select("user_id").distinct().withColumn("name", F.concat(F.lit("u"), F.col("user_id").cast("string")))
    assert collect(streams.enrich(timed(), users), "enriched", tmp_path).where("name is not null").count() == p.count()
    got = collect(streams.meetings(timed(), timed()), "met", tmp_path).where("a_point_id >= 0").count()
    batch = p.withColumn("ts", F.col("ts").cast("timestamp"))
    assert got == streams.meetings(batch, batch).count() > 0


def test_late_points_are_dropped(spark, tmp_path):
    path, p = replay(spark, tmp_path, 2)
    late = p.limit(3).withColumn("point_id", F.col("point_id") + 10**6).withColumn("ts", F.lit("2023-01-01").cast("timestamp_ntz"))
    late.coalesce(1).write.mode("append").parquet(path)
    w = streams.window_nodes(streams.with_event_time(streams.points_stream(spark, path), "1 hour"), "1 day")
    q = w.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "late")).start()
    q.processAllAvailable()
    # the three points fall into one, two or three windows and cells, and each dropped row of the merged counts is one of those
    assert 1 <= streams.late_rows(q) <= 3
    q.stop()
    assert spark.table("late").where("start < '2023-06-01'").count() == 0


def test_update_and_complete_modes(spark, tmp_path):
    path, p = replay(spark, tmp_path)
    for mode in ("update", "complete"):
        w = streams.window_nodes(streams.with_event_time(streams.points_stream(spark, path)), "1 day")
        q = w.writeStream.format("memory").queryName(mode).outputMode(mode).option("checkpointLocation", str(tmp_path / mode)).start()
        q.processAllAvailable()
        q.stop()
        last = spark.table(mode).where("start < '2024-02-15'").groupBy("start", "end", "cx", "cy").agg(F.max("n").alias("n"))
        assert last.agg(F.sum("n")).first()[0] == p.count()
    assert spark.table("complete").groupBy("start", "cx", "cy").count().where("count > 1").count() == 0


def test_a_refreshed_graph_survives_repeated_batches_and_compaction(spark, tmp_path):
    mv, path = build_movements(carriers.points(spark, SF)), str(tmp_path / "cube")
    put = streams.refresh(path)
    for i in (0, 1, 1, 2):
        put(mv.where(F.col("movement_id") % 3 == i), i)
    rows = lambda df: sorted(map(tuple, df.select(sorted(df.columns)).collect()))
    whole = aggregate.pyramid_nodes(mv)
    before = rows(streams.refreshed(spark, path))
    assert rows(streams.kept_nodes(spark, path)) == rows(summarize.significant_nodes(whole))
    streams.compact(spark, path)
    assert rows(streams.refreshed(spark, path)) == before == rows(aggregate.pyramid_nodes(mv, time_bin="day"))
    assert rows(streams.refreshed(spark, path, "edges")) == rows(aggregate.pyramid_edges(mv, time_bin="day"))
    put(mv.where("false"), 3)
    assert rows(streams.kept_nodes(spark, path)) == rows(summarize.significant_nodes(whole))
