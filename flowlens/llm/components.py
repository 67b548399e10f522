"""Distributed connected components by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize


def connected_components(edges: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """(node, component): component is the smallest node id reachable.

    Each round every node merges into its neighbour (or itself) of least pseudo-random priority, which shrinks the graph by a
    constant factor whatever its shape (chains, stars, cliques). Edges, parents and labels stay in shared tables; only the
    number of remaining edges reaches the driver. Null ends and loops are ignored; an empty input gives an empty result.
    """
    node_type = dict(edges.dtypes)[u]
    e = edges.select(F.col(u).alias("u"), F.col(v).alias("v")).where("u is not null and v is not null and u <> v")
    e = materialize(e.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct())
    labels = None
    while not e.isEmpty():
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        near = both.groupBy("u").agg(F.min(F.struct(F.xxhash64("v").alias("h"), F.col("v").alias("n"))).alias("m"))
        parent = materialize(near.select(F.col("u").alias("node"), F.least("m", F.struct(F.xxhash64("u").alias("h"), F.col("u").alias("n")))["n"].alias("parent")))
        if labels is None:
            labels = parent
        else:
            up = parent.select(F.col("node").alias("parent"), F.col("parent").alias("next"))
            labels = materialize(labels.join(up, "parent", "left").select("node", F.coalesce("next", "parent").alias("parent")))
        pu = parent.select(F.col("node").alias("u"), F.col("parent").alias("pu"))
        pv = parent.select(F.col("node").alias("v"), F.col("parent").alias("pv"))
        e = e.join(pu, "u").join(pv, "v").where("pu <> pv").select(F.least("pu", "pv").alias("u"), F.greatest("pu", "pv").alias("v"))
        e = materialize(e.distinct())
    if labels is None:
        return e.sparkSession.createDataFrame([], f"node {node_type}, component {node_type}")
    least = materialize(labels.groupBy("parent").agg(F.min(F.least("node", "parent")).alias("component")))
    return labels.join(least, "parent").select("node", "component")
