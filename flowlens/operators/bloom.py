"""Bloom filters, one per level: sizing, building from cell ids, probing, and edge filtering with its exact counterparts."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.grid import cell_id

KEY = ["level", "cx", "cy"]
# Fixed values of the double hash: two multipliers, two offsets and a prime modulus.
M1, A1, M2, A2, PRIME = 2654435761, 97, 40503, 12345, 2147483647
#: Bytes of all filters together that are still broadcast; beyond, edges are filtered by joins.
MAX_BYTES = 512 << 20
#: Bytes of one level's filter, which is one value of a broadcast row.
LEVEL_BYTES = 128 << 20


def size(n: int, fpp: float = 0.01) -> tuple[int, int]:
    """(bits, hashes) for n members at a false-positive share."""
    if n == 0:
        return 1, 1
    m = math.ceil(-n * math.log(fpp) / math.log(2) ** 2)
    return m, max(1, round(m / n * math.log(2)))


def tune(n: int, max_bytes: int | None = None, fpp: float = 0.01) -> tuple[int, int]:
    """size(), but no larger than max_bytes; the hashes then follow from the bits."""
    m, k = size(n, fpp)
    if max_bytes is not None and m > 8 * max_bytes:
        m = 8 * max_bytes
        k = max(1, round(m / max(n, 1) * math.log(2)))
    return m, k


def position(ident: Column, i: Column, m: Column) -> Column:
    """Bit of the ith hash: (h1 + i * h2) mod m in whole numbers that any engine repeats."""
    ident = ident.cast("long")
    h1 = (ident * F.lit(M1).cast("long") + A1) % F.lit(PRIME).cast("long")
    h2 = (ident * F.lit(M2).cast("long") + A2) % F.lit(PRIME).cast("long") + 1
    return (h1 + i * h2) % m


def sizes(kept: DataFrame, fpp: float = 0.01, max_bytes: int | None = None) -> dict[int, tuple[int, int, int]]:
    """level -> (members, bits, hashes). One row a level reaches the driver."""
    return {r["level"]: (r["c"], *tune(r["c"], max_bytes, fpp)) for r in kept.groupBy("level").agg(F.count("*").alias("c")).collect()}


def set_bits(kept: DataFrame, dims: dict[int, tuple[int, int, int]]) -> DataFrame:
    """(level, pos) of all set bits."""
    spark = kept.sparkSession
    table = F.broadcast(spark.createDataFrame([(lv, m, k) for lv, (_, m, k) in dims.items()], "level int, m long, k int"))
    each = kept.select(*KEY).join(table, "level").withColumn("i", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    return each.select("level", position(cell_id(F.col("cx"), F.col("cy")), F.col("i").cast("long"), F.col("m")).alias("pos")).distinct()


def bitmaps(bits: DataFrame) -> DataFrame:
    """(level, bucket, bitmap): pages of 4 KB, merged on the way to the shuffle."""
    return bits.groupBy("level", F.bitmap_bucket_number(F.col("pos") + 1).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("pos") + 1)).alias("bitmap"))


def filters(kept: DataFrame, fpp: float = 0.01, max_bytes: int | None = None) -> dict[int, tuple[int, int, np.ndarray]] | None:
    """level -> (bits, hashes, byte array), or None where a level's filter would pass LEVEL_BYTES or all together MAX_BYTES. All levels
    are built in one aggregate; kept should be a stored table, as it is read for the sizes and for the bits."""
    dims = sizes(kept, fpp, max_bytes)
    if sum(m for _, m, _ in dims.values()) > 8 * MAX_BYTES or any(m > 8 * LEVEL_BYTES for _, m, _ in dims.values()):
        return None
    page = 32768
    out = {lv: (m, k, np.zeros(-(-m // page) * page // 8, np.uint8)) for lv, (_, m, k) in dims.items()}
    for r in bitmaps(set_bits(kept, dims)).collect():
        at = (r["bucket"] - 1) * page // 8
        out[r["level"]][2][at : at + page // 8] = np.frombuffer(r["bitmap"], np.uint8)
    return out


def probe(levels: np.ndarray, idents: np.ndarray, held: dict[int, tuple[int, int, np.ndarray]]) -> np.ndarray:
    """Which ids pass the filter of their level; a level without a filter passes nothing. The probe of a Python client."""
    out = np.zeros(len(idents), bool)
    h1, h2 = (idents * M1 + A1) % PRIME, (idents * M2 + A2) % PRIME + 1
    for lv in np.unique(levels):
        if int(lv) in held:
            m, k, bits = held[int(lv)]
            at = np.flatnonzero(levels == lv)
            ok = np.ones(len(at), bool)
            for i in range(k):
                p = (h1[at] + i * h2[at]) % m
                ok &= bits[p >> 3] >> (p & 7) & 1 == 1
            out[at] = ok
    return out


def filter_table(spark, held: dict[int, tuple[int, int, np.ndarray]]) -> DataFrame:
    """(_level, _m, _k, _words): a row a level, its bits as whole numbers of 64."""
    rows = [(lv, m, k, np.concatenate([bits, np.zeros(-len(bits) % 8, np.uint8)]).view(np.int64)) for lv, (m, k, bits) in held.items()]
    frame = pa.table({"_level": pa.array([r[0] for r in rows], pa.int32()), "_m": pa.array([r[1] for r in rows], pa.int64()), "_k": pa.array([r[2] for r in rows], pa.int32()), "_words": pa.array([r[3] for r in rows], pa.list_(pa.int64()))})
    return spark.createDataFrame(frame)


def passes(cx: Column, cy: Column, hashes: int) -> Column:
    """Whether a cell passes the filter in _m, _k and _words, in generated code: one array element a hash, the first miss decides."""
    ident = cell_id(cx, cy)
    ok = F.lit(True)
    for i in range(hashes):
        p = position(ident, F.lit(i).cast("long"), F.col("_m"))
        word = F.get(F.col("_words"), F.shiftright(p, 6).cast("int"))
        bit = F.call_function("shiftright", word, p.bitwiseAND(63).cast("int")).bitwiseAND(1) == 1
        ok = ok & ((F.lit(i) >= F.col("_k")) | bit)
    return ok


def bloom_filter_edges(edges: DataFrame, kept: DataFrame, fpp: float = 0.01, max_bytes: int | None = None) -> DataFrame:
    """Edges whose both ends pass: no edge between kept nodes is lost, few others slip in. Edges are not shuffled: the filters, one row
    a level, are broadcast, and each edge tests its bits where it is. Beyond the bounds on the filters' bytes, two semi-joins decide."""
    held = filters(kept, fpp, max_bytes)
    if held is None:
        return join_filter_edges(edges, kept)
    hashes = max((k for _, k, _ in held.values()), default=1)
    wide = edges.join(F.broadcast(filter_table(edges.sparkSession, held)), F.col("level") == F.col("_level"))
    return wide.where(passes(F.col("sx"), F.col("sy"), hashes) & passes(F.col("tx"), F.col("ty"), hashes)).select(*edges.columns)


def join_filter_edges(edges: DataFrame, kept: DataFrame, how: str | None = None) -> DataFrame:
    """The exact answer by two semi-joins; how: a join hint."""
    side = kept.hint(how) if how else kept
    for x, y in (("sx", "sy"), ("tx", "ty")):
        edges = edges.join(side.select("level", F.col("cx").alias(x), F.col("cy").alias(y)), ["level", x, y], "left_semi")
    return edges.select("level", "sx", "sy", "tx", "ty", *[c for c in edges.columns if c not in ("level", "sx", "sy", "tx", "ty")])
