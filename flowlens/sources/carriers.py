"""Points and movements made from the given tables by an integer geocoder (FIXTURES.md F1 to F4)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geo import great_circle_km
from .tables import table

# Fixed values of the geocoder: two linear scatters, the anchor lattice and the clamp.
A_MUL, A_ADD, A_MOD = 1103515245, 12345, 2147483648
B_MUL, B_ADD, B_MOD = 214013, 2531011, 2147483647
X_MAX, Y_MAX = 399_359_999, 276_479_999


def _div(a: Column, b: int) -> Column:
    return F.floor(a / F.lit(b)) if isinstance(a, int) else F.call_function("div", a, F.lit(b).cast("long"))


def scatter_a(k: Column) -> Column:
    return (k * F.lit(A_MUL).cast("long") + A_ADD) % F.lit(A_MOD).cast("long")


def scatter_b(k: Column) -> Column:
    return (k * F.lit(B_MUL).cast("long") + B_ADD) % F.lit(B_MOD).cast("long")


def anchor_xy(i: Column) -> tuple[Column, Column]:
    i = i.cast("long")
    ax = ((i * 7 + 3) % 26) * 15_360_000 + ((i * 5381) % 15_360) * 1000
    ay = ((i * 11 + 5) % 18) * 15_360_000 + ((i * 7919) % 15_360) * 1000
    return ax, ay


def place(anchor: Column, spread: Column, key: Column) -> tuple[Column, Column]:
    ax, ay = anchor_xy(anchor)
    at = lambda a, r, top: F.greatest(F.least(a + _div(spread * (_div(r, 128) % 2001), 8) - spread * 125, F.lit(top).cast("long")), F.lit(0).cast("long"))
    return at(ax, scatter_a(key), X_MAX), at(ay, scatter_b(key), Y_MAX)


def points_from_events(events: DataFrame) -> DataFrame:
    """point_id, user_id, ts, x_mas, y_mas, event_type, value, props."""
    spread = F.round(F.col("value") * 100).cast("long")
    b = scatter_b(F.col("event_id"))
    u = (F.col("user_id") * 48271 + 11) % F.lit(B_MOD).cast("long")
    q = F.when(_div(b, 7) % 8 == 0, _div(b, 64) % 100).otherwise(u % 100)
    x, y = place(_div(q * q, 400), spread, F.col("event_id"))
    return events.select(F.col("event_id").alias("point_id"), "user_id", "ts", x.alias("x_mas"), y.alias("y_mas"), "event_type", "value", "props")


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points_from_events(table(spark, sf_dir, "events"))


def shipments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Origin-destination movements from supplier to customer, one per order line."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_shipdate", "l_returnflag", "l_extendedprice")
    order = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    end = lambda nation, key, bal, x, y: dict(zip((x, y), place(F.col(nation), _div(F.round((F.col(bal) + 1000) * 100).cast("long"), 64), F.col(key))))
    supplier = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal").withColumns(end("s_nationkey", "s_suppkey", "s_acctbal", "sx", "sy"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment").withColumns(end("c_nationkey", "c_custkey", "c_acctbal", "tx", "ty"))
    # supplier and customer are dimension tables; whether they are broadcast is left to their measured size
    mv = line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    mv = mv.select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("t0"), F.col("l_shipdate").alias("t1"), "sx", "sy", "tx", "ty", "l_returnflag", "l_extendedprice", "o_orderpriority", "c_mktsegment", "s_nationkey", "c_nationkey")
    return mv.withColumn("dist_km", great_circle_km(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty")))
