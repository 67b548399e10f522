"""Exact top-k Hamming search by incremental multi-index hashing.

A binary code is cut into segments, and each segment has a table of its values. A query probes all tables at segment radius 0, 1, ...;
once radius s is done in the first j of m tables, every code within m*s + j - 1 bits has been seen (pigeonhole), so the search stops as
soon as the kth verified distance is no larger.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, n_partitions, scratch, table

BITS = 64
#: Codes of a shard at most and at least (smaller tables have fewer shards than tasks), and query codes that meet a shard at a time.
CELL_CODES, LEAST_CODES, CELL_QUERIES = 1_000_000, 8_000, 100_000


def sign_code(vector: Column, bits: int = BITS) -> Column:
    """Bit i is set where element i is positive; missing and null elements give 0. Null for a null vector."""
    code = F.lit(0).cast("long")
    for i in range(bits):
        code = code.bitwiseOR(F.when(F.get(vector, F.lit(i)) > 0, F.lit(1 << i if i < 63 else -(1 << 63)).cast("long")).otherwise(F.lit(0).cast("long")))
    return F.when(vector.isNotNull(), code)


def masks(width: int, radius: int) -> np.ndarray:
    """All values of `width` bits with `radius` ones."""
    return np.array([sum(1 << b for b in c) for c in combinations(range(width), radius)], dtype=np.int64)


class MultiIndex:
    """Tables of the segments of distinct codes. A table lists code positions by segment value (one sorted array and its starts)."""

    def __init__(self, codes: np.ndarray, holders: np.ndarray, bits: int = BITS):
        self.codes, self.holders, self.bits = codes, holders, bits
        self.balls: dict[tuple[int, int], np.ndarray] = {}
        # segments of about log2(n) bits, at most 16, so that a bucket holds a few codes
        self.m = max(1, math.ceil(bits / min(16, max(4, int(math.log2(max(2, len(codes))))))))
        edges = np.linspace(0, bits, self.m + 1).astype(int)
        self.cuts = list(zip(edges[:-1].tolist(), np.diff(edges).tolist()))
        self.tables = []
        for shift, width in self.cuts:
            v = ((codes >> np.uint64(shift)) & np.uint64((1 << width) - 1)).astype(np.int64)
            order = np.argsort(v, kind="stable")
            self.tables.append((order, np.concatenate([[0], np.cumsum(np.bincount(v, minlength=1 << width))])))

    def search(self, query: int, k: int) -> np.ndarray:
        """Positions of all codes no further than the kth holder (a code counts as often as it has holders)."""
        n = len(self.codes)
        q = np.uint64(query)
        seen = np.zeros(n, bool)
        at = [np.zeros(0, np.int64)]
        within = np.zeros(self.bits + 1, np.int64)  # holders by verified distance
        for radius in range(max(w for _, w in self.cuts) + 1):
            for j, ((shift, width), (order, starts)) in enumerate(zip(self.cuts, self.tables)):
                if math.comb(width, radius) <= n and (width, radius) not in self.balls:
                    self.balls[width, radius] = masks(width, radius)
                probe = (int(query) >> shift & (1 << width) - 1) ^ self.balls.get((width, radius), np.zeros(0, np.int64))
                if math.comb(width, radius) > n:  # more buckets than codes: verify the rest directly
                    found = np.flatnonzero(~seen)
                    covered = self.bits
                else:
                    lo, size = starts[probe], starts[probe + 1] - starts[probe]
                    total = int(size.sum())
                    found = order[np.repeat(lo - np.cumsum(size) + size, size) + np.arange(total)] if total else at[0]
                    found = found[~seen[found]]
                    covered = self.m * radius + j
                if len(found):
                    seen[found] = True
                    at.append(found)
                    within += np.bincount(np.bitwise_count(self.codes[found] ^ q), weights=self.holders[found], minlength=self.bits + 1).astype(np.int64)
                if within[: covered + 1].sum() >= k or covered >= self.bits or seen.all():
                    got = np.concatenate(at)
                    d = np.bitwise_count(self.codes[got] ^ q)
                    need = int(np.searchsorted(np.cumsum(within), k))  # the kth distance
                    return got[d <= need]
        return np.concatenate(at)


def top_k(rows: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, rank, neighbour_id, distance) of the k rows nearest to every query row by (distance, id), itself left out.

    rows, queries: (id, code). Codes are made distinct first with their k + 1 smallest ids, so a code that a third of all rows share
    is one entry. Codes are dealt to shards by hash, each code to one; a shard builds its tables once for up to CELL_QUERIES query
    codes, which go to all shards, and the shards' answers are merged. Null codes or ids are left out; fewer than k other rows give
    fewer results; repeated rows count once; an empty table gives an empty result.
    """
    spark = rows.sparkSession
    with scratch(spark):
        by_code = Window.partitionBy("code").orderBy("id")
        clean = rows.where("code is not null and id is not null").select("id", "code").distinct()
        least = clean.withColumn("_r", F.row_number().over(by_code)).where(F.col("_r") <= k + 1)
        codes = materialize(least.groupBy("code").agg(F.sort_array(F.collect_list("id")).alias("ids")))
        asked = materialize(queries.where("code is not null and id is not null").select("id", "code").distinct(), lasting=True)
        ask_codes = materialize(asked.select("code").distinct())
        n = codes.count()
        shards = max(1, -(-n // CELL_CODES), min(n_partitions(spark), n // LEAST_CODES))
        blocks = max(1, -(-ask_codes.count() // CELL_QUERIES))
        shard, block = F.pmod(F.xxhash64("code"), F.lit(shards)), F.pmod(F.xxhash64("code", F.lit(7)), F.lit(blocks))
        left = codes.withColumns({"shard": shard, "block": F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<long>"))})
        right = ask_codes.withColumns({"block": block, "shard": F.explode(F.sequence(F.lit(0), F.lit(shards - 1)).cast("array<long>"))})

        def cell(index: pa.Table, ask: pa.Table) -> pa.Table:
            out = []
            if index.num_rows and ask.num_rows:
                code = index.column("code").to_numpy().astype(np.int64).view(np.uint64)
                ids = index.column("ids").to_pylist()
                mi = MultiIndex(code, np.array([len(i) for i in ids]))
                for q in ask.column("code").to_pylist():
                    u = q & (1 << 64) - 1
                    found = sorted((int(np.bitwise_count(code[p] ^ np.uint64(u))), i) for p in mi.search(u, k + 1).tolist() for i in ids[p])[: k + 1]
                    out += [(q, i, d) for d, i in found]
            cols = list(zip(*out)) or [(), (), ()]
            return pa.table({"code": pa.array(cols[0], pa.int64()), "neighbour_id": pa.array(cols[1], pa.int64()), "distance": pa.array(cols[2], pa.int32())})

        # a fixed number of partitions: the work is in the searches, which the size of the rows that are dealt does not show
        tasks = min(shards * blocks, max(shards, n_partitions(spark)))
        left, right = (df.repartition(tasks, "shard", "block") for df in (left, right))
        found = left.groupBy("shard", "block").cogroup(right.groupBy("shard", "block")).applyInArrow(cell, "code long, neighbour_id long, distance int")
        found = materialize(found, lasting=True)
    best = Window.partitionBy("query_id").orderBy("distance", "neighbour_id")
    pairs = asked.withColumnRenamed("id", "query_id").join(found, "code").where("query_id <> neighbour_id")
    return pairs.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "neighbour_id", "distance")


def op7_multi_index_hamming(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), sign_code(F.col("embedding")).alias("code"))
    return top_k(rows, rows.where("id % 100 = 0"))


ORACLE = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x > 0) AS b FROM embeddings WHERE embedding IS NOT NULL),
p AS (SELECT q.vec_id AS query_id, r.vec_id AS neighbour_id,
    CAST(list_sum(list_transform(range(1, 65), lambda i: CASE WHEN q.b[i] <> r.b[i] THEN 1 ELSE 0 END)) AS INTEGER) AS distance
  FROM v q JOIN v r ON q.vec_id <> r.vec_id WHERE q.vec_id % 100 = 0),
k AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY distance, neighbour_id) AS INTEGER) AS rank FROM p)
SELECT query_id, rank, neighbour_id, distance FROM k WHERE rank <= 10
"""
