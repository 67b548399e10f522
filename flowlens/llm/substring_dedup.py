"""Exact substring dedup: remove every byte that a long string covers which also starts earlier in the corpus.

Strings of `length` bytes are assigned to anchors: the string's pick among its hashed `gram`-byte grams. Equal strings pick the same gram
at the same place, so only strings of one anchor value have to be compared, and an anchor with its run of strings is a segment of some
135 bytes. Segments seen once are dropped, equal segments are settled by their first occurrence, and the distinct segments of an anchor
go together into a suffix array (built by grouping) over symbols that stand for runs of columns in which the same segments agree; where
neighbours have `length` columns in common, strings are equal.
Anchors with very many distinct segments are first split by longer cores of their strings, so no group is ever collected whole.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_lookup, materialize, n_partitions, scratch, slices, table
from .shingles import BASE, Powers, mixed
from .suffix_array import common_prefixes, suffix_array

LENGTH, GRAM = 100, 32
#: Distinct segments of an anchor that one suffix array may hold, and bytes that one suffix array takes before the next is begun.
GROUP_CAP, ARRAY_BYTES = 4096, 1 << 19
#: Share of documents whose anchors are counted to find the values to spread over partitions (layout only, results never depend on it).
SAMPLE_OF = 64
BLOCK = 1 << 22
#: Columns added to documents for a while; no table has such names.
SPANS, SPANS_ID, NUM, DIGEST, PLACE = "__flowlens_spans", "__flowlens_id", "__flowlens_num", "__flowlens_md5", "__flowlens_place"


def range_hash(total: np.ndarray, up: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return (total[end] - total[start]) * up[start]


def anchors(raw: np.ndarray, powers: Powers, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(anchor hash, segment hash, first string start, anchor position, number of strings) of every segment of a text."""
    n = len(raw)
    if n < length:
        none = np.zeros(0, np.int64)
        return none.astype(np.uint64), none.astype(np.uint64), none, none, none
    up, down = powers.upto(n + 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * down[:n], dtype=np.uint64)])
    h = mixed((total[gram:] - total[:-gram]) * up[: n - gram + 1])
    w = length - gram + 1  # grams of a string
    picks = []
    for b in range(0, n - length + 1, BLOCK):
        part = h[b : b + BLOCK + w - 1]
        # high bits of the hash, then the position: the least value is the pick, the leftmost of equal ones
        low = (part & np.uint64(~0x7FFFFF & (1 << 64) - 1)) | np.arange(len(part), dtype=np.uint64)
        span = 1
        while 2 * span <= w:
            low = np.minimum(low[: len(low) - span], low[span:])
            span *= 2
        low = np.minimum(low[: len(part) - w + 1], low[w - span : w - span + len(part) - w + 1])
        picks.append((low & np.uint64(0x7FFFFF)).astype(np.int64) + b)
    pick = np.concatenate(picks)
    first = np.flatnonzero(np.concatenate([[True], pick[1:] != pick[:-1]]))
    count = np.diff(np.append(first, len(pick)))
    at = pick[first]
    end = first + count - 1 + length
    seg = mixed(range_hash(total, up, first, end) + mixed((end - first).astype(np.uint64) * np.uint64(BASE) + (at - first).astype(np.uint64)))
    return h[at], seg, first, at, count


def raw_bytes(text: str | None) -> np.ndarray:
    return np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)


def segments(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(ah, sh, doc_id, loc) of all segments; loc packs the first string's start, the anchor's offset in it and the number of strings."""

    def run(batches):
        powers = Powers()
        for b in slices(batches):
            out = [[], [], [], []]
            for i, t in zip(b.column(0).to_pylist(), b.column(1)):
                ah, sh, first, at, count = anchors(raw_bytes(t.as_py()), powers, length, gram)
                if len(ah):
                    for col, v in zip(out, (ah.view(np.int64), sh.view(np.int64), np.full(len(ah), i, np.int64), (first << 20) | (at - first) << 10 | count)):
                        col.append(v)
            if out[0]:
                yield pa.record_batch([pa.array(np.concatenate(c)) for c in out], ["ah", "sh", "doc_id", "loc"])

    return docs.mapInArrow(run, "ah long, sh long, doc_id long, loc long")


def settle(rows: DataFrame) -> DataFrame:
    """From rows sorted by (ah, sh, doc_id, loc) in each partition: (later, ah, sh, doc_id, loc). later: an equal segment precedes in the
    partition. The others are passed on where their anchor has several distinct segments here or is spread over partitions (hot)."""

    def run(batches):
        last, held = None, None  # keys of the last row; a first row whose anchor has no second segment so far
        for b in batches:
            if not b.num_rows:
                continue
            ah, sh, doc, loc = (b.column(i).to_numpy() for i in range(4))
            hot = b.column(4).to_numpy(zero_copy_only=False)
            same = np.concatenate([[last is not None and last == (ah[0], sh[0])], (ah[1:] == ah[:-1]) & (sh[1:] == sh[:-1])])
            last = (ah[-1], sh[-1])
            f = np.flatnonzero(~same)
            cols = [np.zeros(0, np.int64)] * 4
            if len(f) or held is not None:
                head = [np.concatenate([[x] if held is not None else np.zeros(0, np.int64), v[f]]).astype(np.int64) for x, v in zip(held[:4] if held is not None else [0] * 4, (ah, sh, doc, loc))]
                force = np.concatenate([[held[4]] if held is not None else [], hot[f]]).astype(bool)
                sent = np.concatenate([[held[5]] if held is not None else [], np.zeros(len(f), bool)]).astype(bool)
                near = head[0][1:] == head[0][:-1]
                go = force | np.concatenate([[False], near]) | np.concatenate([near, [False]])
                held = tuple(int(v[-1]) for v in head) + (bool(force[-1]), bool(go[-1] or sent[-1]))
                cols = [v[go & ~sent] for v in head]
            late = [v[same] for v in (ah, sh, doc, loc)]
            flag = np.concatenate([np.ones(len(late[0]), bool), np.zeros(len(cols[0]), bool)])
            if len(flag):
                yield pa.record_batch([pa.array(flag)] + [pa.array(np.concatenate(p)) for p in zip(late, cols)], ["later", "ah", "sh", "doc_id", "loc"])

    return rows.mapInArrow(run, "later boolean, ah long, sh long, doc_id long, loc long")


def quotient(rows: list[np.ndarray], first: np.ndarray, reach: int, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Strings of symbols for groups of segments that are aligned at their anchors. rows: bytes of every segment, group by group, all
    groups of the same size; first: (groups, members) column of every segment's first byte.

    Neighbouring columns in which the same members agree are one symbol, so two segments agree on a part of a symbol only if they
    agree on all of it, and nothing that a comparison could tell is lost. All strings hold the anchor, so a segment counts only up to
    the columns on either side of it in which no other agrees with it, and not at all if `length` columns do not remain. Returns
    (labels, live, starts, ends): the member that a cell's value is first met in, the cells that count, whether a symbol begins at a
    column of a group, and the column after a segment's last live cell.
    """
    width = reach + length
    groups, members = first.shape
    cells = np.full((groups, members, width), 256, np.uint16) + np.arange(members, dtype=np.uint16)[None, :, None]
    flat = cells.reshape(-1, width)
    for r, (at, data) in enumerate(zip(first.ravel(), rows)):
        flat[r, at : at + len(data)] = data
    order = np.argsort(cells, axis=1, kind="stable")
    value = np.take_along_axis(cells, order, 1)
    head = np.ones(cells.shape, bool)
    head[:, 1:] = value[:, 1:] != value[:, :-1]
    lead = np.maximum.accumulate(np.where(head, np.arange(members)[None, :, None], 0), axis=1)
    labels, alone = np.empty_like(order), np.empty_like(head)
    np.put_along_axis(labels, order, np.take_along_axis(order, lead, 1), 1)
    np.put_along_axis(alone, order, head & np.concatenate([head[:, 1:], np.ones((groups, 1, width), bool)], axis=1), 1)
    right, left = alone[:, :, reach + gram :], alone[:, :, :reach][:, :, ::-1]
    ends = reach + gram + np.where(right.any(2), right.argmax(2), right.shape[2])
    begins = reach - np.where(left.any(2), left.argmax(2), left.shape[2])
    at = np.arange(width)
    live = (at >= begins[:, :, None]) & (at < ends[:, :, None]) & (ends - begins >= length)[:, :, None]
    starts = np.ones((groups, width), bool)
    starts[:, 1:] = ((labels[:, :, 1:] != labels[:, :, :-1]) & live[:, :, 1:] | (live[:, :, 1:] != live[:, :, :-1])).any(axis=1)
    return labels, live, starts, ends


def longest_to_earlier(shared: list[int], rank: list[int]) -> list[int]:
    """For entries in suffix order, the longest common prefix with any entry of smaller rank. shared[k]: columns that k has in common
    with k - 1. The nearest smaller rank on either side is the best one there, so two sweeps with a stack suffice."""
    n = len(rank)
    best = [0] * n
    for forward in (True, False):
        stack: list[tuple[int, int]] = []  # (rank, columns in common with the entry below)
        for step in range(n):
            k = step if forward else n - 1 - step
            m = shared[k] if forward else (shared[k + 1] if k + 1 < n else 0)
            if not m:
                stack = []
            while stack and stack[-1][0] > rank[k]:
                m = min(m, stack.pop()[1])
            if stack:
                best[k] = max(best[k], m)
            stack.append((rank[k], m))
    return best


def repeated_ranges(key: np.ndarray, start: np.ndarray, off: np.ndarray, segs: list[bytes], length: int, gram: int) -> list[tuple[int, int, int]]:
    """(row, start, end) byte ranges of all strings of `length` bytes that an earlier row of the same key holds at the same place about
    its anchor. Rows are sorted by key and then by the order that says which is earlier; off: the anchor's place in the segment."""
    reach = length - gram
    width = reach + length
    cut = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    size = np.diff(np.append(cut, len(key)))
    text, owner, column, run_end, base = [], [], [], [], 0
    for members in np.unique(size):
        if members < 2:
            continue
        heads = cut[size == members]
        for lot in range(0, len(heads), max(1, 4096 // members)):
            rows = (heads[lot : lot + max(1, 4096 // members), None] + np.arange(members)[None, :]).ravel()
            first = (reach - off[rows]).reshape(-1, members)
            labels, live, starts, ends = quotient([np.frombuffer(segs[r], np.uint8) for r in rows], first, reach, length, gram)
            g, m, c = np.nonzero(starts[:, None, :] & live)
            if not len(g):
                continue
            symbol = ((base + g) * width + c) * (1 << 20) + labels[g, m, c]
            base += len(first)
            row = rows.reshape(-1, members)[g, m]
            # every segment ends in a symbol of its own, one column past its last live cell
            last = np.flatnonzero(np.append(row[1:] != row[:-1], True))
            ends = ends[g[last], m[last]]
            text.append(np.insert(symbol, last + 1, -1 - row[last]))
            owner.append(np.insert(row, last + 1, row[last]))
            column.append(np.insert(c, last + 1, ends))
    if not text:
        return []
    text, owner, column = (np.concatenate(v) for v in (text, owner, column))
    run_end = np.append(column[1:], 0)  # where the symbol at a position ends
    symbols = text.tolist()
    order = suffix_array(symbols)
    depth = np.array(common_prefixes(symbols, order))
    order = np.array(order)
    columns = np.where(depth > 0, column[np.minimum(order + depth, len(column) - 1)] - column[order], 0)
    columns[columns < length] = 0
    used = np.flatnonzero((columns > 0) | np.append(columns[1:] > 0, False))
    best = np.array(longest_to_earlier(columns[used].tolist(), owner[order[used]].tolist()), dtype=np.int64)
    found = used[best >= length]
    at, best = order[found], best[best >= length]
    # strings may start anywhere in the first symbol as long as the common columns last
    more = np.minimum(best - length, run_end[at] - column[at] - 1)
    row = owner[at]
    begin = start[row] + column[at] - (reach - off[row])
    return list(zip(row.tolist(), begin.tolist(), (begin + more + length).tolist()))


def array_kernel(length: int, gram: int, array_bytes: int):
    """mapInArrow kernel over rows (key, doc_id, start, off, seg) sorted by key, doc_id and start: ranges of repeated strings."""

    def solve(rows):
        key, doc, start, off, segs = zip(*rows)
        found = repeated_ranges(np.array(key, np.int64), np.array(start, np.int64), np.array(off, np.int64), list(segs), length, gram)
        row, begin, end = zip(*found) if found else ((), (), ())
        return pa.record_batch([pa.array([doc[r] for r in row], pa.int64()), pa.array(begin, pa.int64()), pa.array(end, pa.int64())], ["doc_id", "start", "end"])

    def run(batches):
        held, size, key = [], 0, None
        for b in slices(batches):
            for row in zip(*(c.to_pylist() for c in b.columns)):
                if size >= array_bytes and row[0] != key:
                    yield solve(held)
                    held, size = [], 0
                held.append(row)
                size, key = size + len(row[4]), row[0]
        if held:
            yield solve(held)

    return run


RANGES = "doc_id long, start long, end long"


def first_only(rows: DataFrame, by: list[str]) -> tuple[DataFrame, DataFrame]:
    """(first rows by (doc_id, loc) of every value of `by`, the others)."""
    head = materialize(rows.groupBy(*by).agg(F.min(F.struct("doc_id", "loc")).alias("_f")))
    both = materialize(rows.join(head, by))
    is_first = (F.col("doc_id") == F.col("_f.doc_id")) & (F.col("loc") == F.col("_f.loc"))
    return both.where(is_first).drop("_f").distinct(), both.where(~is_first).drop("_f")


def removed_ranges(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, group_cap: int = GROUP_CAP, array_bytes: int = ARRAY_BYTES) -> DataFrame:
    """(doc_id, start, end) byte ranges that earlier equal strings cover; ranges of one document may overlap. docs: (doc_id, text), one
    row an id."""
    docs = docs.where("doc_id is not null and text is not null")
    parts = n_partitions(docs.sparkSession)
    seen = segments(docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE_OF)) == 0), length, gram).groupBy("ah").agg(F.count("*").alias("_n"))
    seen = materialize(seen.where("_n > 1"))
    bound = max(8, (seen.agg(F.sum("_n")).first()[0] or 0) // (4 * parts))
    hot = seen.where(F.col("_n") >= bound).select("ah", F.lit(True).alias("hot"))  # at most 4 values a partition
    rows = join_lookup(segments(docs, length, gram), hot, "ah").withColumn("hot", F.coalesce("hot", F.lit(False)))
    place = F.when(F.col("hot"), F.xxhash64("ah", "sh", F.pmod(F.xxhash64("doc_id"), F.lit(parts)))).otherwise(F.xxhash64("ah"))
    rows = rows.repartition(parts, place).sortWithinPartitions("ah", "sh", "doc_id", "loc")
    settled = materialize(settle(rows))
    start, strings = F.shiftright("loc", 20), F.col("loc").bitwiseAND(1023)
    as_range = lambda df: df.select("doc_id", start.alias("start"), (start + strings - 1 + length).alias("end"))
    out = as_range(settled.where("later"))
    firsts, others = first_only(settled.where("not later").drop("later"), ["ah", "sh"])
    out = out.unionByName(as_range(others))
    several = materialize(firsts.groupBy("ah").agg(F.count("*").alias("_m")).where("_m > 1"))
    wanted = firsts.join(several.select("ah"), "ah")

    # the bytes of the segments, cut out of each text once
    asked = materialize(wanted.groupBy("doc_id").agg(F.collect_list(F.struct("ah", "loc")).alias("asked")))

    def cut(batches):
        for b in slices(batches):
            rows = []
            for i, t, asked in zip(*(c.to_pylist() for c in b.columns)):
                raw = (t or "").encode("utf-8", "surrogatepass")
                for a in asked:
                    s, off, n = a["loc"] >> 20, a["loc"] >> 10 & 1023, a["loc"] & 1023
                    rows.append((a["ah"], i, s, off, raw[s : s + n - 1 + length]))
            if rows:
                yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()))], ["key", "doc_id", "start", "off", "seg"])

    pieces = docs.join(asked, "doc_id").select("doc_id", "text", "asked").mapInArrow(cut, "key long, doc_id long, start long, off int, seg binary")
    pieces = materialize(pieces.distinct())
    lo, hi = 0, length - gram  # anchors lie at most hi bytes into a string
    todo = [(pieces, lo, hi)]
    kernel = array_kernel(length, gram, array_bytes)
    while todo:
        part, lo, hi = todo.pop()
        sizes = part.groupBy("key").agg(F.count("*").alias("_m"))
        large = materialize(sizes.where(F.col("_m") > group_cap).select("key"))
        if large.isEmpty():
            ready, crowd = part, None
        else:
            ready, crowd = part.join(large, "key", "left_anti"), materialize(part.join(large, "key"))
        ready = ready.select("key", "doc_id", "start", "off", "seg").repartition(parts, "key").sortWithinPartitions("key", "doc_id", "start")
        out = out.unionByName(materialize(ready.mapInArrow(kernel, RANGES)))
        if crowd is not None:
            # strings whose anchor is o bytes in, by halves of o: all strings of a half hold a longer core around the anchor
            mid = (lo + hi) // 2
            for a, b in ((lo, mid), (mid + 1, hi)) if lo < hi else ():
                narrow, rest = split_by_core(crowd, a, b, length)
                out = out.unionByName(rest)
                todo.append((narrow, a, b))
    return out


def split_by_core(rows: DataFrame, a: int, b: int, length: int) -> tuple[DataFrame, DataFrame]:
    """Strings with a <= anchor offset <= b of the segments, regrouped by their common core; (distinct segments that share their core
    with others, ranges of segments that repeat an earlier one)."""
    # a string starting x bytes into the segment has its anchor off - x bytes in
    x0, x1 = F.greatest(F.lit(0), F.col("off") - b), F.least(F.col("off") - a, F.length("seg") - length)
    cut = rows.withColumns({"_x0": x0, "_x1": x1}).where("_x0 <= _x1")
    cut = cut.select("key", "doc_id", (F.col("start") + F.col("_x0")).alias("start"), (F.col("off") - F.col("_x0")).cast("int").alias("off"), F.expr(f"substring(seg, cast(_x0 + 1 as int), cast(_x1 - _x0 + {length} as int))").alias("seg"))
    # the core reaches from a bytes before the anchor to the end of the string whose anchor is b bytes in
    core = F.expr(f"substring(seg, cast(off - {a} + 1 as int), {length - b + a})")
    cut = cut.select(F.xxhash64("key", core, F.lit(a)).alias("key"), "doc_id", F.col("start").alias("loc"), "off", "seg")
    firsts, others = first_only(cut, ["key", "off", "seg"])
    ranges = others.select("doc_id", F.col("loc").alias("start"), (F.col("loc") + F.length("seg")).cast("long").alias("end"))
    several = materialize(firsts.groupBy("key").agg(F.count("*").alias("_m")).where("_m > 1").select("key"))
    return materialize(firsts.join(several, "key").select("key", "doc_id", F.col("loc").alias("start"), "off", "seg")), ranges


def keep_mask(n: int, spans: list[dict] | None) -> tuple[np.ndarray, int]:
    """(bytes kept, number of maximal removed runs)."""
    edge = np.zeros(n + 1, np.int32)
    for s in spans or ():
        edge[s["start"]] += 1
        edge[s["end"]] -= 1
    gone = np.cumsum(edge[:n]) > 0
    return ~gone, int(np.count_nonzero(np.diff(np.concatenate([[False], gone]).astype(np.int8)) == 1))


def documents_of(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows with the column NUM, (doc_id, text) with NUM as doc_id and one row a document). NUM orders documents.

    A document is an id with a text: rows that repeat both are one, and further texts of an id are documents after it, in order of
    the text's MD5 (null as empty). While no id repeats, NUM is the id; else it is the place of (id, MD5) in a range sort. Rows
    without an id have no NUM.
    """
    ids = docs.withColumn(NUM, F.col("doc_id").cast("long"))
    if ids.where(f"{NUM} is not null").groupBy(NUM).count().where("count > 1").isEmpty():
        return ids, ids.select(F.col(NUM).alias("doc_id"), "text")
    keyed = ids.withColumn(DIGEST, F.md5(F.coalesce("text", F.lit("")).cast("binary")))
    names = keyed.where(f"{NUM} is not null").select(F.col(NUM).alias(SPANS_ID), F.col(DIGEST).alias(SPANS)).distinct()
    names = names.repartitionByRange(n_partitions(docs.sparkSession), SPANS_ID, SPANS).sortWithinPartitions(SPANS_ID, SPANS)
    names = materialize(names.withColumn(PLACE, F.monotonically_increasing_id()))
    placed = keyed.join(names, (keyed[NUM] == names[SPANS_ID]) & (keyed[DIGEST] == names[SPANS]), "left").drop(NUM, DIGEST, SPANS_ID, SPANS)
    placed = materialize(placed.withColumnRenamed(PLACE, NUM), lasting=True)
    once = placed.where(f"{NUM} is not null").groupBy(F.col(NUM).alias("doc_id")).agg(F.first("text").alias("text"))
    return placed, materialize(once)


def with_ranges(docs: DataFrame, length: int, gram: int, group_cap: int = GROUP_CAP) -> DataFrame:
    """Rows with the column SPANS: their documents' removed ranges."""
    with scratch(docs.sparkSession):
        rows, once = documents_of(docs)
        ranges = removed_ranges(once, length, gram, group_cap)
        spans = materialize(ranges.groupBy(F.col("doc_id").alias(SPANS_ID)).agg(F.collect_set(F.struct("start", "end")).alias(SPANS)), lasting=True)
    return rows.join(spans, rows[NUM] == spans[SPANS_ID], "left").drop(SPANS_ID, NUM)


def dedup_digest(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, group_cap: int = GROUP_CAP) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document row.

    Strings are judged on the input; matches never cross documents; null texts are empty. Rows that repeat an id and its text are one
    document and get one result each; several texts of one id are documents that follow one another in order of their MD5. Rows
    without an id are left whole; an empty table gives an empty result.
    """

    def run(batches):
        for b in slices(batches):
            rows = []
            for i, t, spans in zip(*(c.to_pylist() for c in b.columns)):
                raw = raw_bytes(t)
                keep, runs = keep_mask(len(raw), spans)
                rows.append((i, len(raw), int(len(raw) - keep.sum()), runs, hashlib.sha256(raw[keep].tobytes()).hexdigest()))
            if rows:
                yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string()))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    rows = with_ranges(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), length, gram, group_cap)
    return rows.select("doc_id", "text", SPANS).mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def dedup_texts(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """The rows with repeated strings cut out of `text`; all other columns pass through. Characters that a cut splits are dropped whole."""
    rows = with_ranges(docs, length, gram)

    def run(batches):
        for b in slices(batches):
            k, s = b.schema.get_field_index("text"), b.schema.get_field_index(SPANS)
            out = []
            for t, spans in zip(b.column(k).to_pylist(), b.column(s).to_pylist()):
                if spans:
                    raw = raw_bytes(t)
                    t = raw[keep_mask(len(raw), spans)[0]].tobytes().decode("utf-8", "ignore")
                out.append(t)
            cols = [pa.array(out, pa.string()) if i == k else c for i, c in enumerate(b.columns) if i != s]
            yield pa.record_batch(cols, [n for i, n in enumerate(b.schema.names) if i != s])

    return rows.mapInArrow(run, docs.schema)


def op5_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_digest(table(spark, sf_dir, "documents"))
