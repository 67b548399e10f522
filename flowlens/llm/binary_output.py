"""Token-id output: best-fit-decreasing packing with a segment tree over free capacities, lossless splits, packed id matrices."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import table
from .tokens import END_OF_TEXT, default_vocabulary, encoder, largest_id, split_points

CAP = 2048
#: Tokens that a task holds before it packs and writes them; this bounds its memory whatever the input.
BUFFER_TOKENS = 6_000_000

SCHEMA = "sequence_id long, n_tokens int, ids binary, cu_seqlens array<int>, position_resets array<int>, doc_ids array<long>, starts array<long>"


class CapacityTree:
    """Bins by free capacity. A complete binary tree says which capacities occur, so the least one that suffices is a climb and a descent."""

    def __init__(self, cap: int):
        self.size = 1 << cap.bit_length()
        self.has = bytearray(2 * self.size)
        self.bins: list[list[int]] = [[] for _ in range(self.size)]

    def add(self, free: int, which: int) -> None:
        self.bins[free].append(which)
        i = self.size + free
        while i and not self.has[i]:
            self.has[i] = 1
            i >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        """(free, bin) of a bin of least free capacity >= need, taken out."""
        i = self.size + need
        if not self.has[i]:
            while i > 1 and (i & 1 or not self.has[i + 1]):  # climb until a right neighbour holds something larger
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.size:
                i = 2 * i if self.has[2 * i] else 2 * i + 1
        free = i - self.size
        which = self.bins[free].pop()
        if not self.bins[free]:
            self.has[i] = 0
            i >>= 1
            while i and not (self.has[2 * i] or self.has[2 * i + 1]):
                self.has[i] = 0
                i >>= 1
        return free, which


def best_fit_decreasing(sizes: list[int], cap: int) -> list[list[int]]:
    """Items by bin, largest first, each into the fullest bin that still holds it. Ties keep input order."""
    tree, bins = CapacityTree(cap), []
    for item in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        found = tree.take(sizes[item])
        if found is None:
            found = cap, len(bins)
            bins.append([])
        free, which = found
        bins[which].append(item)
        tree.add(free - sizes[item], which)
    return bins


def position_ids(cu_seqlens: list[int]) -> np.ndarray:
    """Positions within segments, which restart at every cumulative length."""
    ends = np.asarray(cu_seqlens)
    return np.arange(ends[-1]) - np.repeat(ends[:-1], np.diff(ends)) if len(ends) > 1 else np.zeros(0, int)


def pack_documents(docs: DataFrame, cap: int = CAP, vocabulary: str | None = None, separator: int = END_OF_TEXT[1], id_col: str = "doc_id", text_col: str = "text", buffer_tokens: int = BUFFER_TOKENS) -> DataFrame:
    """Packed sequences: ids (little-endian, 16 bits a token where the vocabulary allows, else 32), cumulative segment lengths from 0,
    offsets at which positions restart, and the document and token start of every segment.

    A document is its tokens and the separator; longer ones than cap are cut losslessly. No shuffle: every task packs its own input
    in buffers of bounded size. Null and empty texts are one separator; repeated rows are packed as often as they come; rows without
    an id are packed with a null one; an empty table gives an empty result.
    """
    vocabulary = vocabulary or default_vocabulary()

    def flush(held: list[tuple[int, int, np.ndarray]], base: int) -> Iterator[pa.RecordBatch]:
        bins = best_fit_decreasing([len(ids) for _, _, ids in held], cap)
        for k in range(0, len(bins), 512):
            rows = []
            for j, items in enumerate(bins[k : k + 512]):
                ids = np.concatenate([held[i][2] for i in items])
                ends = np.cumsum([0] + [len(held[i][2]) for i in items]).tolist()
                rows.append((base + k + j, len(ids), ids.astype(width).tobytes(), ends, ends[:-1], [held[i][0] for i in items], [held[i][1] for i in items]))
            kinds = [pa.int64(), pa.int32(), pa.binary(), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.int64())]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], ["sequence_id", "n_tokens", "ids", "cu_seqlens", "position_resets", "doc_ids", "starts"])

    width = "<u2" if max(separator, largest_id(vocabulary)) < 1 << 16 else "<u4"

    def run(batches):
        from pyspark import TaskContext

        encode, held, tokens = encoder(vocabulary), [], 0
        base = TaskContext.get().partitionId() << 40
        for b in batches:
            for i, text in zip(b.column(0).to_pylist(), b.column(1)):
                ids = np.append(encode(text.as_py() or ""), np.uint32(separator))
                for s, n in split_points(len(ids), cap):
                    held.append((i, s, ids[s : s + n].copy() if n < len(ids) else ids))
                tokens += len(ids)
                if tokens >= buffer_tokens:
                    done = 0
                    for out in flush(held, base):
                        done += out.num_rows
                        yield out
                    base, held, tokens = base + done, [], 0
        yield from flush(held, base)

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, SCHEMA)


def op1_bfd_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
