"""Bulk-synchronous best-fit packing of whole documents into sequences.

Documents are range-sorted by length. Gaps of open sequences and waiting documents are then runs of equal size, at most `cap` of
either, however many there are. A superstep takes the longest waiting run, sweeps to the successor among the gap runs (the smallest
gap that holds it) and matches as many as both runs have; rank inside the runs settles which document gets which gap. Gaps shrink,
unmatched documents open sequences, and the next superstep follows. Only run lengths reach the driver; every document then finds its
place from its rank by a join with the list of matched runs.
"""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_lookup, materialize, n_partitions, scratch, slices, table
from .tokens import default_vocabulary, encoder, split_points

CAP = 2048
SEPARATOR = 0
#: Ranks of a length are looked up in blocks of this many bits.
RANK_BITS = 12

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"


def token_pieces(docs: DataFrame, cap: int = CAP, vocabulary: str | None = None, separator: int = SEPARATOR, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece: a document's tokens and the separator, cut only beyond cap tokens. Null and
    empty texts are the separator alone; null ids stay null; repeated rows give their pieces again; an empty table gives none."""
    vocabulary = vocabulary or default_vocabulary()
    names, kinds = ["doc_id", "piece", "start", "length", "ids_crc32"], [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]

    def run(batches):
        encode = encoder(vocabulary)
        for b in slices(batches):
            rows = []
            for i, text in zip(b.column(0).to_pylist(), b.column(1)):
                ids = np.append(encode(text.as_py() or ""), np.uint32(separator)).astype("<u4")
                rows += [(i, k, s, n, zlib.crc32(ids[s : s + n].tobytes())) for k, (s, n) in enumerate(split_points(len(ids), cap))]
            if rows:
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, PIECE_SCHEMA)


def supersteps(waiting: dict[int, int], cap: int) -> list[tuple[int, int, int, int, int, int]]:
    """Matched runs (length, first rank, last rank + 1, first sequence, documents a sequence, offset) for counts of waiting documents by length.

    A gap that holds several documents of a run takes them in one superstep, as they would follow one another into it anyway.
    """
    gaps: dict[int, list[tuple[int, int, int]]] = defaultdict(list)  # free -> runs of (first sequence, sequences, used)
    sizes: list[int] = []
    out, sequences = [], 0

    def put(first: int, count: int, used: int) -> None:
        free = cap - used
        if count and free:
            if free not in gaps or not gaps[free]:
                bisect.insort(sizes, free)
            gaps[free].append((first, count, used))

    for length in sorted(waiting, reverse=True):
        rank, left = 0, waiting[length]
        while left:
            at = bisect.bisect_left(sizes, length)  # successor sweep
            if at < len(sizes):
                free = sizes[at]
                first, count, used = gaps[free].pop()
                if not gaps[free]:
                    sizes.pop(at)
            else:
                free, used, first = cap, 0, sequences
                count = -(-left // (cap // length))
                sequences += count
            each = free // length
            whole = min(count, left // each)
            if whole:
                out.append((length, rank, rank + whole * each, first, each, used))
                put(first, whole, used + each * length)
                rank, left = rank + whole * each, left - whole * each
            rest = min(left, each) if whole < count and left < each else 0
            if rest:
                out.append((length, rank, rank + rest, first + whole, rest, used))
                put(first + whole, 1, used + rest * length)
                rank, left = rank + rest, 0
            put(first + whole + bool(rest), count - whole - bool(rest), used)
    return out


def pack(pieces: DataFrame, cap: int = CAP) -> DataFrame:
    """The pieces (doc_id, piece, length, ...) with sequence_id and offset. Lengths must lie in 1..cap; other columns pass through.

    Ranks come from one range sort: every partition's position and, for each length it holds, how many precede. Repeated rows are
    placed as often as they come; an empty table gives an empty result.
    """
    spark = pieces.sparkSession
    # the sort key ends in the piece's own identity, so a length shared by a third of all rows still spreads over partitions
    ranged = pieces.repartitionByRange(n_partitions(spark), F.col("length").desc(), "doc_id", "piece").sortWithinPartitions(F.col("length").desc(), "doc_id", "piece")
    ranged = materialize(ranged.withColumn("_at", F.monotonically_increasing_id()), lasting=True)
    part = F.shiftright("_at", 33)
    # at most cap + partitions rows: a length spans neighbouring partitions only
    runs = ranged.groupBy(F.col("length").alias("length"), part.alias("_p")).agg(F.min("_at").alias("_first"), F.count("*").alias("_n")).collect()
    before: dict[int, int] = defaultdict(int)
    bases = []
    for r in sorted(runs, key=lambda r: (r["length"], r["_p"])):
        bases.append((r["length"], r["_p"], before[r["length"]] - r["_first"]))
        before[r["length"]] += r["_n"]
    base = spark.createDataFrame(bases, "length long, _p long, _shift long")
    plan = spark.createDataFrame(supersteps(dict(before), cap), "length long, _lo long, _hi long, _seq long, _each long, _off long")
    # a document meets the matched runs of its block of ranks only, by an equi-join
    blocks = F.sequence(F.shiftright("_lo", RANK_BITS), F.shiftright(F.col("_hi") - 1, RANK_BITS))
    plan = plan.withColumn("_block", F.explode(blocks))
    ranked = join_lookup(ranged.withColumn("_p", part), base, ["length", "_p"], "inner").withColumn("_rank", F.col("_at") + F.col("_shift"))
    ranked = ranked.withColumn("_block", F.shiftright("_rank", RANK_BITS))
    placed = join_lookup(ranked, plan, ["length", "_block"], "inner").where("_rank >= _lo and _rank < _hi")
    i = F.col("_rank") - F.col("_lo")
    return placed.select(*[c for c in pieces.columns], (F.col("_seq") + F.floor(i / F.col("_each"))).alias("sequence_id"), (F.col("_off") + i % F.col("_each") * F.col("length")).alias("offset"))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    with scratch(spark):
        return pack(materialize(token_pieces(table(spark, sf_dir, "documents"))))
