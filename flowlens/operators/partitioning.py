"""Spatial partitioning learned from a sample: recursive bisection, lookups, halo search and placement."""

from __future__ import annotations

import warnings
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..config import RegionSpec

#: Rows that a sample brings to the driver at most.
SAMPLE_ROWS = 1_000_000


def sample(df: DataFrame, fraction: float, seed: int = 42, how: str = "modulus", key: str = "movement_id") -> DataFrame:
    """A share of the rows: by an arithmetic hash of the key (repeatable in any engine), by chance, or exactly so many by least hash."""
    if how == "modulus":
        return df.where((F.col(key) * 48271 + seed) % 2147483647 % 10_000 < int(fraction * 10_000))
    if how == "bernoulli":
        return df.sample(fraction, seed)
    if how == "reservoir":
        return df.orderBy(F.xxhash64(F.col(key), F.lit(seed)), key).limit(int(fraction))
    raise ValueError(f"unknown sampling {how}")


@dataclass(frozen=True)
class Leaf:
    leaf: int
    x0: int
    y0: int
    x1: int
    y1: int


@dataclass
class PartitionTree:
    """Disjoint rectangles that cover a region, and the cuts that made them: (axis, position, below, above) or a leaf number."""

    leaves: list[Leaf]
    cuts: object

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame([(v.leaf, v.x0, v.y0, v.x1, v.y1) for v in self.leaves], "leaf int, x0 long, y0 long, x1 long, y1 long")


def _cut(values: np.ndarray, weights: np.ndarray, share: float) -> tuple[float, int] | None:
    """(imbalance, position) of the cut between distinct values that comes nearest to the share; None if all values are one."""
    order = np.argsort(values, kind="stable")
    v, w = values[order], np.cumsum(weights[order])
    places = np.flatnonzero(v[1:] != v[:-1])
    if not len(places):
        return None
    miss = np.abs(w[places] - share * w[-1])
    k = int(np.argmin(miss))
    return float(miss[k] / w[-1]), int(v[places[k] + 1])


def bisect(points: np.ndarray, k: int, region: RegionSpec = RegionSpec(), axis: str = "best", weights: np.ndarray | None = None) -> PartitionTree:
    """Cut the region into k rectangles of like weight. points: rows (x, y). best: the axis with the better balance at every cut;
    alternate: x and y in turn; stripes: equal widths along x. An odd k splits in proportion. Where no cut separates the points,
    fewer leaves come out, with a warning."""
    weights = np.ones(len(points)) if weights is None else np.asarray(weights, float)
    leaves: list[Leaf] = []

    def grow(idx: np.ndarray, want: int, box: tuple[int, int, int, int], depth: int):
        x0, y0, x1, y1 = box
        if want > 1:
            low = want // 2
            cuts = {a: _cut(points[idx, a], weights[idx], low / want) if len(idx) else None for a in (0, 1)}
            usable = {a: c for a, c in cuts.items() if c}
            if axis == "alternate" and depth % 2 in usable:
                usable = {depth % 2: usable[depth % 2]}
            if axis == "stripes":
                usable = {0: (0.0, x0 + (x1 - x0) * low // want)}
            if usable:
                a = min(usable, key=lambda a: (usable[a][0], a))
                at = usable[a][1]
                left = points[idx, a] < at
                boxes = ((x0, y0, at, y1), (at, y0, x1, y1)) if a == 0 else ((x0, y0, x1, at), (x0, at, x1, y1))
                return (a, at, grow(idx[left], low, boxes[0], depth + 1), grow(idx[~left], want - low, boxes[1], depth + 1))
            warnings.warn(f"{want} partitions asked where the sample has one position", stacklevel=2)
        leaves.append(Leaf(len(leaves), *box))
        return len(leaves) - 1

    return PartitionTree(leaves, grow(np.arange(len(points)), k, (0, 0, region.width, region.height), 0)) if k > 0 else PartitionTree([], None)


def learn(rows: DataFrame, k: int, x: str = "x", y: str = "y", weight: str | None = None, axis: str = "best", region: RegionSpec = RegionSpec()) -> PartitionTree:
    """bisect() on the distinct positions of the rows, weighed by how many rows (or how much weight) each holds. Beyond SAMPLE_ROWS
    positions, those of least hash stand for all, each with its whole weight, so no part of the input is preferred."""
    held = rows.groupBy(F.col(x).alias("_x"), F.col(y).alias("_y")).agg((F.sum(weight) if weight else F.count("*")).cast("double").alias("_w"))
    held = held.withColumn("_h", F.pmod(F.xxhash64("_x", "_y"), F.lit(1 << 20)))
    share = SAMPLE_ROWS / max(1, held.count())
    got = (held if share >= 1 else held.where(F.col("_h") < int(share * (1 << 20)))).select("_x", "_y", "_w").toPandas()
    return bisect(got[["_x", "_y"]].to_numpy(np.int64), k, region, axis, got["_w"].to_numpy())


def range_bounds(keys: DataFrame, k: int, key: str = "key") -> list[int]:
    """k - 1 keys that cut a sample (SAMPLE_ROWS at most, by hash of the key) into runs of like length, as range placement does."""
    share = SAMPLE_ROWS / max(1, keys.count())
    some = keys if share >= 1 else keys.where(F.pmod(F.xxhash64(key), F.lit(1 << 20)) < int(share * (1 << 20)))
    held = np.sort(some.select(key).toPandas()[key].to_numpy(np.int64))
    return [int(held[i * len(held) // k]) for i in range(1, k)] if len(held) else []


def by_bounds(key: Column, bounds: list[int]) -> Column:
    """How many bounds a key has reached: its range."""
    return sum((F.when(key >= b, 1).otherwise(0) for b in bounds), F.lit(0))


def hash_slot(k: int, *cols: str) -> Column:
    """The partition that repartition(k, cols) sends a row to."""
    return F.pmod(F.hash(*cols), F.lit(k))


def by_cuts(tree: PartitionTree, x: Column, y: Column) -> Column:
    """Leaf of a position as nested comparisons, which stay in generated code."""

    def build(node):
        if isinstance(node, int):
            return F.lit(node)
        a, at, below, above = node
        return F.when((x if a == 0 else y) < at, build(below)).otherwise(build(above))

    return build(tree.cuts)


def packed_rtree(leaves: list[Leaf], fanout: int = 8) -> list[np.ndarray]:
    """Levels of a sort-tile-recursive R-tree, leaves first; rows (x0, y0, x1, y1, first child or leaf number, children)."""
    rows = np.array([(v.x0, v.y0, v.x1, v.y1, v.leaf, 0) for v in leaves], np.int64)
    strips = max(1, int(np.ceil(np.sqrt(len(rows) / fanout))))
    order = np.argsort(rows[:, 0] + rows[:, 2], kind="stable")
    per = -(-len(rows) // strips)
    order = np.concatenate([o[np.argsort(rows[o, 1] + rows[o, 3], kind="stable")] for o in (order[i : i + per] for i in range(0, len(order), per))])
    levels = [rows[order]]
    while len(levels[-1]) > 1:
        below = levels[-1]
        starts = range(0, len(below), fanout)
        levels.append(np.array([(*below[s : s + fanout, :2].min(0), *below[s : s + fanout, 2:4].max(0), s, len(below[s : s + fanout])) for s in starts], np.int64))
    return levels


def rtree_search(levels: list[np.ndarray], x0: int, y0: int, x1: int, y1: int) -> list[int]:
    """Leaves whose half-open rectangles meet the closed box."""
    at = np.arange(len(levels[-1]))
    for depth in range(len(levels) - 1, -1, -1):
        nodes = levels[depth][at]
        hit = nodes[(nodes[:, 0] <= x1) & (nodes[:, 2] > x0) & (nodes[:, 1] <= y1) & (nodes[:, 3] > y0)]
        if depth == 0:
            return sorted(hit[:, 4].tolist())
        at = np.concatenate([np.arange(s, s + n) for s, n in hit[:, 4:6]]) if len(hit) else np.zeros(0, int)
    return []


def rtree_locate(levels: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The leaf of every position, -1 outside all: a whole batch goes down the tree level by level."""
    out = np.full(len(x), -1, np.int64)
    who, at = np.arange(len(x)).repeat(len(levels[-1])), np.tile(np.arange(len(levels[-1])), len(x))
    for depth in range(len(levels) - 1, -1, -1):
        n = levels[depth][at]
        ok = (n[:, 0] <= x[who]) & (n[:, 2] > x[who]) & (n[:, 1] <= y[who]) & (n[:, 3] > y[who])
        who, n = who[ok], n[ok]
        if depth == 0:
            out[who] = n[:, 4]
        else:
            many = n[:, 5]
            who = who.repeat(many)
            at = np.repeat(n[:, 4] - np.cumsum(many) + many, many) + np.arange(many.sum())
    return out


def lookup(df: DataFrame, tree: PartitionTree, method: str = "cut_tree", x: str = "x", y: str = "y") -> DataFrame:
    """The rows with their leaf. cut_tree: nested comparisons; rtree: a packed tree that each task loads once; linear: every leaf is tried."""
    if method == "cut_tree":
        return df.withColumn("leaf", by_cuts(tree, F.col(x), F.col(y)).cast("int"))
    spark = df.sparkSession
    if method == "linear":
        leaves = tree.frame(spark)  # one row a partition, bounded by the partition count
        hit = (F.col(x) >= F.col("x0")) & (F.col(x) < F.col("x1")) & (F.col(y) >= F.col("y0")) & (F.col(y) < F.col("y1"))
        return df.join(F.broadcast(leaves), hit).drop("x0", "y0", "x1", "y1")
    if method == "rtree":
        shared = spark.sparkContext.broadcast(packed_rtree(tree.leaves))

        def run(batches):
            levels = shared.value
            for b in batches:
                xs, ys = (b.column(b.schema.get_field_index(c)).fill_null(-1).to_numpy().astype(np.int64) for c in (x, y))
                found = rtree_locate(levels, xs, ys)
                yield pa.record_batch([*b.columns, pa.array(found, pa.int32(), mask=found < 0)], [*b.schema.names, "leaf"])

        return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("leaf", T.IntegerType())]))
    raise ValueError(f"unknown lookup {method}")


def leaves_within(df: DataFrame, tree: PartitionTree, offset: str, x: str = "x", y: str = "y") -> DataFrame:
    """One row for every leaf that the box around a position meets; offset names the column with its half side."""
    leaves = tree.frame(df.sparkSession)
    meets = (F.col("x0") <= F.col(x) + F.col(offset)) & (F.col("x1") > F.col(x) - F.col(offset)) & (F.col("y0") <= F.col(y) + F.col(offset)) & (F.col("y1") > F.col(y) - F.col(offset))
    return df.join(F.broadcast(leaves), meets).drop("x0", "y0", "x1", "y1")


def place(df: DataFrame, k: int, by: str = "leaf") -> DataFrame:
    """One Spark partition per leaf, or hash or range placement for comparison."""
    if by == "leaf":
        return df.repartitionById(k, F.col("leaf"))
    if by == "hash":
        return df.repartition(k, "level", "cx", "cy")
    if by == "range":
        from ..functions.grid import morton

        return df.repartitionByRange(k, "level", morton(F.col("cx"), F.col("cy")))
    raise ValueError(f"unknown placement {by}")
