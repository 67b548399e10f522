"""MinHash near-duplicates with sequential Bayesian verification.

Texts with one shingle set are one node. Nodes that share a band of their signatures are candidates; a candidate's signatures are
compared batch by batch and it is dropped as soon as the posterior probability of a similarity at or above the threshold falls below
the chosen miss probability; survivors are verified on full shingle sets. Every bucket first compares its members with one leader.
Later only members outside a bucket's largest component are compared with the rest, in blocks of signatures, so that linked groups are
never expanded into pairs and no pair becomes a row before it has survived.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, n_partitions, scratch, slices, table
from .components import connected_components
from .shingles import Powers, coefficients, minhash, shingle_set

#: Similarity at or above which documents are linked, as a ratio of whole numbers.
NUM, DEN = 75, 100
BANDS, ROWS, BATCH = 32, 4, 16
#: Probability at most that verification drops a pair at the threshold.
MISS = 1e-7
#: Side of the cells in which members of one bucket are compared, and pairs from which a bucket is regrouped by rare shingles.
CELL, HOT_PAIRS = 1024, 1 << 26


@dataclass(frozen=True)
class Params:
    num: int = NUM
    den: int = DEN
    bands: int = BANDS
    rows: int = ROWS
    batch: int = BATCH
    miss: float = MISS


def posterior_tail(matches: int, seen: int, t: float, steps: int = 2000) -> float:
    """P(similarity >= t | matches of seen hashes agree) under a uniform prior, by the midpoint rule on the Beta density."""
    s = (np.arange(steps) + 0.5) / steps
    log = matches * np.log(s) + (seen - matches) * np.log1p(-s)
    w = np.exp(log - log.max())
    return float(w[s >= t].sum() / w.sum())


def least_matches(p: Params) -> list[int]:
    """For every batch end, the fewest agreeing hashes at which the posterior still allows the threshold."""
    n, out = p.bands * p.rows, []
    for seen in range(p.batch, n + 1, p.batch):
        out.append(next((m for m in range(seen + 1) if posterior_tail(m, seen, p.num / p.den) >= p.miss), seen))
    return out


def signatures(docs: DataFrame, p: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, h1, h2 (128 bits that identify the shingle set), sig (little-endian 32-bit MinHash values)."""

    def run(batches):
        powers, (a, b) = Powers(), coefficients(p.bands * p.rows)
        for batch in slices(batches):
            n, h1, h2, sig = [], [], [], []
            for t in batch.column(1):
                s = shingle_set(t.as_py(), powers)
                n.append(len(s))
                h1.append(int(np.add.reduce(s, dtype=np.uint64).astype(np.int64)))
                h2.append(int(np.add.reduce(s * (s | np.uint64(1)) ^ (s >> np.uint64(29)), dtype=np.uint64).astype(np.int64)))
                sig.append(minhash(s, a, b).tobytes())
            yield pa.record_batch([batch.column(0), pa.array(n, pa.int64()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(sig, pa.binary())], ["doc_id", "n_shingles", "h1", "h2", "sig"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, "doc_id long, n_shingles long, h1 long, h2 long, sig binary")


def bayes_filter(pairs: DataFrame, p: Params = Params()) -> DataFrame:
    """The pairs (a, b, na, nb, siga, sigb) that sequential verification keeps: (a, b, agree)."""
    bounds, width = least_matches(p), p.bands * p.rows

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            na, nb = (b.column(i).to_numpy().astype(np.int64) for i in (2, 3))
            alive = np.flatnonzero(p.den * np.minimum(na, nb) >= p.num * np.maximum(na, nb))  # sizes alone rule out the rest
            sa, sb = (np.frombuffer(b"".join(b.column(i).to_pylist()), np.uint32).reshape(-1, width) for i in (4, 5))
            agree = np.zeros(b.num_rows, np.int32)
            for k, bound in enumerate(bounds):
                part = slice(k * p.batch, (k + 1) * p.batch)
                agree[alive] += (sa[alive, part] == sb[alive, part]).sum(1).astype(np.int32)
                alive = alive[agree[alive] >= bound]
            keep = pa.array(alive)
            yield pa.record_batch([b.column(0).take(keep), b.column(1).take(keep), pa.array(agree[alive])], ["a", "b", "agree"])

    return pairs.select("a", "b", "na", "nb", "siga", "sigb").mapInArrow(run, "a long, b long, agree int")


def exact_links(pairs: DataFrame, docs: DataFrame, p: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The pairs (a, b) whose full shingle sets reach the threshold, with their intersection and union sizes."""
    pairs = materialize(pairs.select("a", "b").distinct())
    held = shingle_sets(docs, materialize(pairs.select(F.explode(F.array("a", "b")).alias("_id")).distinct()), id_col, text_col)

    def verify(batches):
        for b in slices(batches):
            rows = []
            for x, y, s, t in zip(*(c.to_pylist() for c in b.columns)):
                u, v = np.frombuffer(s, np.uint64), np.frombuffer(t, np.uint64)
                both = intersection(u, v)
                either = len(u) + len(v) - both
                if p.den * both >= p.num * either:
                    rows.append((x, y, both, either))
            if rows:
                yield pa.record_batch([pa.array(c, pa.int64()) for c in zip(*rows)], ["a", "b", "n_both", "n_either"])

    joined = pairs.join(held.select(F.col("_id").alias("b"), F.col("_set").alias("_tb")), "b").join(held.select(F.col("_id").alias("a"), F.col("_set").alias("_ta")), "a")
    return joined.select("a", "b", "_ta", "_tb").mapInArrow(verify, "a long, b long, n_both long, n_either long").distinct()


def shingle_sets(docs: DataFrame, ids: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(_id, _set) sorted 64-bit shingles of the documents with the given ids, from their whole texts."""

    def sets(batches):
        powers = Powers()
        for b in slices(batches):
            yield pa.record_batch([b.column(0), pa.array([shingle_set(t.as_py(), powers).tobytes() for t in b.column(1)], pa.binary())], ["_id", "_set"])

    texts = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_t")).join(ids, "_id")
    return materialize(texts.mapInArrow(sets, "_id long, _set binary"))


def intersection(u: np.ndarray, v: np.ndarray) -> int:
    """Common values of two sorted sets."""
    if len(u) > len(v):
        u, v = v, u
    at = np.searchsorted(v, u)
    at[at == len(v)] = 0
    return int((v[at] == u).sum()) if len(v) else 0


def compare_cell(asks, band, rep, n, comp, ask, sig, p: Params, bounds: list[int]):
    """For every asking member of a cell, (its row, rows that survive the sequential comparison, closest first). Only pairs of different
    components meet; two minors meet once; a pair that shares several buckets meets in that of its first band (-1: wherever it is)."""
    at = np.flatnonzero(~asks)
    for i in np.flatnonzero(asks):
        alive = at[(comp[at] != comp[i]) & (~ask[at] | (rep[at] < rep[i])) & (p.den * np.minimum(n[at], n[i]) >= p.num * np.maximum(n[at], n[i]))]
        agree = np.zeros(len(alive), np.int32)
        for k, bound in enumerate(bounds):
            if not len(alive):
                break
            part = slice(k * p.batch, (k + 1) * p.batch)
            agree += (sig[alive, part] == sig[i, part]).sum(1).astype(np.int32)
            ok = agree >= bound
            alive, agree = alive[ok], agree[ok]
        if len(alive) and band[i] >= 0:
            shared = (sig[alive] == sig[i]).reshape(len(alive), p.bands, p.rows).all(axis=2)
            first = shared.argmax(axis=1) == band[i]
            alive, agree = alive[first], agree[first]
        if len(alive):
            yield i, alive[np.lexsort((rep[alive], -agree))]


def by_cell(batches, width: int, solve):
    """Apply solve to the complete cells of batches sorted by cell; rows: cell, asks, band, rep, n, c, ask, sig (, set)."""
    held, last = [], None
    for b in batches:
        if not b.num_rows:
            continue
        cell = b.column(0).to_numpy()
        cols = [b.column(i).to_numpy(zero_copy_only=False) for i in range(1, 7)]
        cols.append(np.frombuffer(b"".join(b.column(7).to_pylist()), np.uint32).reshape(-1, width))
        if b.num_columns > 8:
            sets = np.empty(b.num_rows, object)
            sets[:] = b.column(8).to_pylist()
            cols.append(sets)
        cut = np.concatenate([[0], np.flatnonzero(cell[1:] != cell[:-1]) + 1, [len(cell)]])
        for lo, hi in zip(cut[:-1], cut[1:]):
            if held and cell[lo] != last:
                yield from solve(last, [np.concatenate(c) for c in zip(*held)])
                held = []
            held.append([c[lo:hi] for c in cols])
            last = cell[lo]
    if held:
        yield from solve(last, [np.concatenate(c) for c in zip(*held)])


def cross_links(members: DataFrame, node: DataFrame, docs: DataFrame, p: Params, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(a, b) links between members of one bucket whose components differ: enough to join all components that any such pair joins.
    members: (k, i, rep, c) with the bucket, its band, the document and its component.

    In a bucket only the members outside its largest component ask (minors); all members answer. Buckets of up to HOT_PAIRS such pairs
    are compared as they are. The work in larger ones, unlinked texts that share a band, would grow with their square: their
    members are regrouped exactly by rare shingles first, and every pair at the threshold meets in one of those groups.
    """
    buckets = open_buckets(members)
    hot = materialize(members.join(buckets.where(F.col("size") * F.col("minors") > HOT_PAIRS), "k").select("rep", "c").distinct())
    links = cell_links(members, buckets.where(F.col("size") * F.col("minors") <= HOT_PAIRS), node, docs, p, id_col, text_col)
    if hot.isEmpty():
        return links
    groups = materialize(rare_groups(hot, docs, p, id_col, text_col))
    return links.unionByName(cell_links(groups, open_buckets(groups), node, docs, p, id_col, text_col))


def open_buckets(members: DataFrame) -> DataFrame:
    """(k, size, major, minors) of the buckets that hold several components."""
    per = members.groupBy("k", "c").agg(F.count("*").alias("m"))
    buckets = per.groupBy("k").agg(F.sum("m").alias("size"), F.max(F.struct("m", "c")).alias("x"), F.count("*").alias("comps")).where("comps > 1")
    return materialize(buckets.select("k", "size", F.col("x.c").alias("major"), (F.col("size") - F.col("x.m")).alias("minors")))


def rare_groups(members: DataFrame, docs: DataFrame, p: Params, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(k, i, rep, c): the members (rep, c) by each of their rarest shingles.

    Shingles are ordered by how many members hold them. Two sets at the threshold share at least num/den of either one's shingles, so
    they share one of its first n - ceil(n * num / den) + 1. What many members have in common comes last and groups nobody.
    """
    held = shingle_sets(docs, members.select(F.col("rep").alias("_id")), id_col, text_col)

    def spread(batches):
        for b in slices(batches, 64):
            sets = [np.frombuffer(s, np.int64) for s in b.column(1).to_pylist()]
            for rep, s in zip(b.column(0).to_pylist(), sets):
                for k in range(0, len(s), 1 << 16):
                    part = s[k : k + (1 << 16)]
                    yield pa.record_batch([pa.array(np.full(len(part), rep, np.int64)), pa.array(part), pa.array(np.full(len(part), len(s), np.int64))], ["rep", "s", "n"])

    rows = materialize(held.mapInArrow(spread, "rep long, s long, n long"))
    often = materialize(rows.groupBy("s").agg(F.count("*").alias("df")).where("df > 1"))
    # a shingle of one member groups nobody but takes a place in the order
    ranked = rows.join(often, "s", "left").withColumn("_r", F.row_number().over(Window.partitionBy("rep").orderBy(F.coalesce("df", F.lit(1)), "s")))
    first = ranked.where((F.col("_r") <= F.col("n") - F.ceil(F.col("n") * p.num / p.den) + 1) & F.col("df").isNotNull())
    return first.select("rep", F.col("s").alias("k"), F.lit(-1).alias("i")).join(members, "rep").select("k", "i", "rep", "c")


def cell_links(members: DataFrame, buckets: DataFrame, node: DataFrame, docs: DataFrame, p: Params, id_col: str, text_col: str) -> DataFrame:
    """The links of cross_links() inside the given buckets. Cells of about CELL minors by CELL members are compared in blocks of
    signatures, and the members that survive somewhere are compared again with their full sets at hand, so a pair never becomes a
    row; a minor that has found a component asks no more of its members."""
    parts = n_partitions(members.sparkSession)
    gt, gq = (F.ceil(F.col(c) / CELL).cast("long") for c in ("size", "minors"))
    open_ = members.join(buckets, "k").withColumns({"gt": gt, "gq": gq, "ask": F.col("c") != F.col("major"), "h": F.xxhash64("rep")})
    spread = lambda g: F.explode(F.sequence(F.lit(0).cast("long"), g - 1))
    answers = open_.select("k", "i", F.pmod("h", "gt").alias("bt"), spread(F.col("gq")).alias("bq"), F.lit(False).alias("asks"), "rep", "c", "ask")
    asks = open_.where("ask").select("k", "i", spread(F.col("gt")).alias("bt"), F.pmod("h", "gq").alias("bq"), F.lit(True).alias("asks"), "rep", "c", "ask")
    cells = materialize(answers.unionByName(asks).select(F.xxhash64("k", "bt", "bq").alias("cell"), "asks", "i", "rep", "c", "ask"))
    bounds, width = least_matches(p), p.bands * p.rows
    layout = ["cell", "asks", "i", "rep", "n", "c", "ask", "sig"]

    def involved(batches):
        def solve(cell, cols):
            asks, band, rep, n, comp, ask, sig = cols
            found = set()
            for i, alive in compare_cell(asks, band, rep, n, comp, ask, sig, p, bounds):
                found.add(int(rep[i]))
                found.update(rep[alive].tolist())
            if found:
                yield pa.record_batch([pa.array([cell] * len(found), pa.int64()), pa.array(sorted(found), pa.int64())], ["cell", "rep"])

        return by_cell(batches, width, solve)

    def ready(df, columns):
        return df.select(*columns).repartition(parts, "cell").sortWithinPartitions("cell", "asks", "rep")

    full = cells.join(node, "rep")
    near = materialize(ready(full, layout).mapInArrow(involved, "cell long, rep long"))
    held = shingle_sets(docs, materialize(near.select(F.col("rep").alias("_id")).distinct()), id_col, text_col)

    def verify(batches):
        def solve(cell, cols):
            asks, band, rep, n, comp, ask, sig, sets = cols
            out = []
            for i, alive in compare_cell(asks, band, rep, n, comp, ask, sig, p, bounds):
                u, met = np.frombuffer(sets[i], np.uint64), set()
                for j in alive.tolist():
                    if comp[j] not in met:
                        v = np.frombuffer(sets[j], np.uint64)
                        both = intersection(u, v)
                        if p.den * both >= p.num * (len(u) + len(v) - both):
                            met.add(comp[j])
                            out.append((min(rep[i], rep[j]), max(rep[i], rep[j])))
            if out:
                a, b = zip(*out)
                yield pa.record_batch([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

        return by_cell(batches, width, solve)

    again = full.join(near, ["cell", "rep"], "left_semi").join(held.select(F.col("_id").alias("rep"), "_set"), "rep")
    return materialize(ready(again, [*layout, "_set"]).mapInArrow(verify, "a long, b long").distinct())


def near_duplicates(docs: DataFrame, p: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document row: doc_id, n_shingles, component_id (smallest id reachable over links), kept (doc_id = component_id).

    Links hold where 100 * |intersection| >= 75 * |union| of distinct 5-word shingles. Null, empty and blank texts have no shingles
    and stay alone; texts under five words are one shingle. Rows that repeat an id are one document with the links of all its
    texts. Rows without an id keep a null component and are kept. An empty table gives an empty result. A pair at the threshold is
    missed with probability below (1 - 0.75^4)^32 + 1e-7, about 5e-6. Sets are sets of 64-bit hashes of shingles, and 128 bits of
    sums over them say which texts have one set, so two different sets of n shingles are taken for one with odds of 2^-128, and a
    pair's overlap is off by one with odds of about n^2 / 2^64.
    """
    with scratch(docs.sparkSession):
        sigs = materialize(signatures(docs, p, id_col, text_col), lasting=True)
        reps = materialize(sigs.where("n_shingles > 0 and doc_id is not null").groupBy("h1", "h2").agg(F.min("doc_id").alias("rep"), F.max("n_shingles").alias("n"), F.max("sig").alias("sig")))
        node = reps.select("rep", "n", "sig")
        keys = node.select("rep", F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.xxhash64(F.lit(i), F.expr(f"substring(sig, {4 * p.rows * i + 1}, {4 * p.rows})")).alias("k")) for i in range(p.bands)])).alias("_b")).select("rep", F.col("_b.i").alias("i"), F.col("_b.k").alias("k"))
        crowded = materialize(keys.groupBy("k").agg(F.count("*").alias("size"), F.min("rep").alias("leader")).where("size > 1"))
        member = materialize(keys.join(crowded, "k").select("k", "i", "rep", "leader").distinct())

        # every member of a bucket against its leader: one partner for every node first, then pairs still apart
        star = member.where("rep <> leader").select(F.col("leader").alias("a"), F.col("rep").alias("b")).distinct()
        a = node.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sig").alias("siga"))
        b = node.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sig").alias("sigb"))
        alive = materialize(bayes_filter(star.join(a, "a").join(b, "b"), p))
        best = alive.groupBy("b").agg(F.max(F.struct("agree", (-F.col("a")).alias("m"))).alias("_x")).select((-F.col("_x.m")).alias("a"), "b")
        links = materialize(exact_links(best, docs, p, id_col, text_col).select("a", "b"))
        comps = materialize(connected_components(links, "a", "b"))
        left = alive.select("a", "b").join(links, ["a", "b"], "left_anti")
        left = left.join(comps.select(F.col("node").alias("a"), F.col("component").alias("ca")), "a", "left").join(comps.select(F.col("node").alias("b"), F.col("component").alias("cb")), "b", "left")
        more = exact_links(left.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")), docs, p, id_col, text_col).select("a", "b")
        links = materialize(links.unionByName(more))
        comps = materialize(connected_components(links, "a", "b"))
        # then members of one bucket in different components
        labelled = member.select("k", "i", "rep").join(comps.select(F.col("node").alias("rep"), "component"), "rep", "left").select("k", "i", "rep", F.coalesce("component", "rep").alias("c"))
        cross = cross_links(materialize(labelled), node, docs, p, id_col, text_col)
        comps = materialize(connected_components(links.unionByName(cross), "a", "b"))
        rep_comp = materialize(reps.select("h1", "h2", "rep").join(comps.select(F.col("node").alias("rep"), "component"), "rep", "left").select("h1", "h2", F.coalesce("component", "rep").alias("_c")), lasting=True)
    out = sigs.select("doc_id", "n_shingles", "h1", "h2").join(rep_comp, ["h1", "h2"], "left")
    comp = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("_c")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", comp.alias("component_id"), F.coalesce(comp == F.col("doc_id"), F.lit(True)).alias("kept"))


def op2_minhash_bayes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
