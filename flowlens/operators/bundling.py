"""Edge bundling that saves ink: edges as 4-D points, a proximity graph, and rounds in which neighbours merge while ink is saved."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.shared import materialize

GOLDEN = (math.sqrt(5) - 1) / 2


#: Points that a block holds about, most blocks that drawings are cut into in all, and sampled points that place the cuts of a block.
BLOCK_POINTS, MAX_BLOCKS, SAMPLED = 8192, 1024, 64
#: Points of a leaf of the tree inside a block, and rows and columns of the distances that are held at once.
LEAF_POINTS, ROWS, COLUMNS = 64, 256, 4096


def ranked(row: np.ndarray, d2: np.ndarray, other: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, rank, other, d2) of the k least of each row by (d2, other)."""
    order = np.lexsort((other, d2, row))
    row, d2, other = row[order], d2[order], other[order]
    first = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else np.zeros(0, np.int64)
    rank = np.arange(len(row)) - np.repeat(first, np.diff(np.append(first, len(row)))) + 1
    use = rank <= k
    return row[use], rank[use], other[use], d2[use]


def distances(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances of all q to all c, added up in the order of the four coordinates."""
    out = np.zeros((len(q), len(c)))
    for i in range(4):
        d = q[:, None, i] - c[None, :, i]
        out += d * d
    return out


def least(d2: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, d2, other) of the k least of each row by (d2, other); infinite distances are none. ids: ascending."""
    at = d2 <= np.partition(d2, k - 1, axis=1)[:, k - 1 : k] if d2.shape[1] > k else np.ones(d2.shape, bool)
    row, col = np.nonzero(at & np.isfinite(d2))
    row, _, col, far = ranked(row, d2[row, col], col, k)
    return row, far, ids[col]


def leaves_of(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, starts): points halved along their widest side until a leaf holds LEAF_POINTS at most, leaf after leaf."""
    parts, stack = [], [np.arange(len(p))]
    while stack:
        at = stack.pop()
        if len(at) <= LEAF_POINTS:
            parts.append(at)
            continue
        axis = int(np.argmax(p[at].max(0) - p[at].min(0)))
        half = len(at) // 2
        at = at[np.argpartition(p[at, axis], half)]
        stack += [at[half:], at[:half]]
    return np.concatenate(parts), np.cumsum([0, *map(len, parts)])[:-1]


def gaps(lo: np.ndarray, hi: np.ndarray, los: np.ndarray, his: np.ndarray) -> np.ndarray:
    """Squared distance of a box to boxes, at most that of any two points of theirs as distances() adds it up."""
    out = np.zeros(np.broadcast_shapes(lo.shape, los.shape)[:-1])
    for i in range(4):
        d = np.maximum(np.maximum(los[..., i] - hi[..., i], lo[..., i] - his[..., i]), 0.0)
        out += d * d
    return out


def tree_nearest(q: np.ndarray, c: np.ndarray, ids: np.ndarray, k: int, bound: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, rank, other, d2) of the k points c nearest to each q by (d2, id), no farther than its squared bound.

    Both are halved into leaves. A leaf of asking points meets the leaves of c from the nearest on, until the next lies beyond all k-th
    neighbours. Of copies of a place only the k of least id can be an answer, and copies that ask are answered once.
    """
    if not len(q) or not len(c):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), ids[:0], np.zeros(0)
    order = np.lexsort((ids, *c.T))
    c, ids = c[order], ids[order]
    first = np.flatnonzero(np.concatenate([[True], (c[1:] != c[:-1]).any(1)]))
    copy = np.arange(len(c)) - np.repeat(first, np.diff(np.append(first, len(c))))
    c, ids = c[copy < k], ids[copy < k]
    places, place = np.unique(q, axis=0, return_inverse=True)
    place = place.ravel()
    far = np.full(len(places), -np.inf)
    np.maximum.at(far, place, np.inf if bound is None else bound)
    order, starts = leaves_of(c)
    c, ids = c[order], ids[order]
    lo, hi = np.minimum.reduceat(c, starts), np.maximum.reduceat(c, starts)
    ends = np.append(starts[1:], len(c))
    asking, begins = leaves_of(places)
    found = []
    for a, b in zip(begins, np.append(begins[1:], len(asking))):
        at = asking[a:b]
        x, most = places[at], far[at].copy()
        away = gaps(x.min(0), x.max(0), lo, hi)
        near = np.argsort(away, kind="stable")
        row, d2, other = np.zeros(0, np.int64), np.zeros(0), ids[:0]
        done, lot = 0, 4
        while done < len(near) and away[near[done]] <= most.max():
            take = near[done : done + lot]
            take = take[away[take] <= most.max()]
            cols = np.concatenate([np.arange(starts[v], ends[v]) for v in take])
            cols = cols[np.argsort(ids[cols], kind="stable")]
            r, e, o = least(distances(x, c[cols]), ids[cols], k)
            row, rank, other, d2 = ranked(np.concatenate([row, r]), np.concatenate([d2, e]), np.concatenate([other, o]), k)
            full = rank == k
            most[row[full]] = np.minimum(most[row[full]], d2[full])
            done, lot = done + lot, min(lot * 2, COLUMNS // LEAF_POINTS)
        found.append((at[row], other, d2))
    row, other, d2 = (np.concatenate(v) for v in zip(*found))
    # from answers of places to those of all that asked
    order = np.lexsort((other, d2, row))
    row, other, d2 = row[order], other[order], d2[order]
    many = np.bincount(row, minlength=len(places))
    begin = np.cumsum(many) - many
    of = np.repeat(np.arange(len(q)), many[place])
    step = np.arange(len(of)) - np.repeat(np.cumsum(many[place]) - many[place], many[place])
    at = begin[place[of]] + step
    return of, step + 1, other[at], d2[at]


def grow_blocks(sample: np.ndarray) -> tuple[list, list]:
    """(nodes, boxes) of a tree of cuts in the middle of the widest side of sampled points. A node is (axis, cut, below, from there on),
    or the number of a block; the blocks' boxes are half-open and cover all of space."""
    nodes, boxes = [], []

    def grow(at: np.ndarray, lo: list, hi: list) -> int:
        me = len(nodes)
        nodes.append(None)
        p = sample[at]
        side = p.max(0) - p.min(0) if len(p) else np.zeros(4)
        axis = int(np.argmax(side))
        if len(at) <= SAMPLED or side[axis] <= 0:
            nodes[me] = len(boxes)
            boxes.append((lo, hi))
            return me
        cut = float(np.sort(p[:, axis])[len(p) // 2])
        if cut <= p[:, axis].min():
            cut = float(p[:, axis][p[:, axis] > cut].min())
        below = p[:, axis] < cut
        left = grow(at[below], lo, [*hi[:axis], cut, *hi[axis + 1 :]])
        nodes[me] = (axis, cut, left, grow(at[~below], [*lo[:axis], cut, *lo[axis + 1 :]], hi))
        return me

    grow(np.arange(len(sample)), [-np.inf] * 4, [np.inf] * 4)
    return nodes, boxes


def blocks_of(p: np.ndarray, nodes: list) -> np.ndarray:
    out, stack = np.zeros(len(p), np.int64), [(0, np.arange(len(p)))]
    while stack:
        node, at = stack.pop()
        if not isinstance(nodes[node], tuple):
            out[at] = nodes[node]
        elif len(at):
            axis, cut, left, right = nodes[node]
            below = p[at, axis] < cut
            stack += [(left, at[below]), (right, at[~below])]
    return out


def coordinates(column: pd.Series) -> np.ndarray:
    return np.array(column.tolist(), float).reshape(len(column), 4)


def _tree_graph(p: DataFrame, k: int, keys: list[str]) -> DataFrame:
    """proximity_graph() by blocks, in a fixed number of jobs. Only drawings of more than a block are cut, by a sample of bounded size, and
    only their points ask other blocks: those that a ball up to their k-th neighbour meets. The driver plans four queries: the points, the
    large drawings, their sample, and the blocks' own answers, which carry each cut point once (rank 0) with what it asks others by."""
    p = materialize(p)
    sizes = p.groupBy(*keys).agg(F.count("*").alias("_n"))
    block = F.greatest(F.lit(BLOCK_POINTS).cast("long"), F.ceil(F.col("_all_n") / MAX_BLOCKS))
    above = sizes.agg(F.coalesce(F.sum("_n"), F.lit(0)).alias("_all_n"), F.collect_list(F.when(F.col("_n") > BLOCK_POINTS, F.struct("_n", *keys))).alias("_big"))
    block, big = above.select(block.alias("_block"), "_big").select("_block", F.filter("_big", lambda v: v["_n"] > F.col("_block"))).first()
    id_type = p.schema["id"].dataType.simpleString()
    graph = f"id {id_type}, rank int, other {id_type}, d2 double"
    tasks = int(p.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def own(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, x = pdf["id"].to_numpy(), coordinates(pdf["p"])
        row, _, other, d2 = tree_nearest(x, x, ids, k + 1)
        use = ids[row] != other
        row, rank, other, d2 = ranked(row[use], d2[use], other[use], k)
        found = pd.DataFrame({"id": ids[row], "rank": rank, "other": other, "d2": d2})
        if "_g" not in pdf or pdf["_g"].iloc[0] < 0:
            return found if "_g" not in pdf else found.assign(p=None, _g=-1, _b=0, far=np.inf)
        far = np.full(len(ids), np.inf)
        far[row[rank == k]] = d2[rank == k]
        asks = pdf[["id", "p", "_g", "_b"]].assign(rank=0, other=ids, d2=0.0, far=far)
        return pd.concat([asks, found.assign(p=None, _g=pdf["_g"].iloc[0], _b=pdf["_b"].iloc[0], far=np.inf)])[["id", "rank", "other", "d2", "p", "_g", "_b", "far"]]

    if not big:
        return p.repartition(tasks, *keys).groupBy(*keys).applyInPandas(own, graph)
    numbered = p.sparkSession.createDataFrame([(*r[1:], i) for i, r in enumerate(big)], T.StructType([*[T.StructField(c, p.schema[c].dataType) for c in keys], T.StructField("_g", T.IntegerType())]))
    p = p.join(F.broadcast(numbered), keys, "left").withColumn("_g", F.coalesce("_g", F.lit(-1)))
    drawn = p.where((F.col("_g") >= 0) & (F.pmod(F.xxhash64("id"), F.lit(block)) < SAMPLED)).select("_g", "p").toPandas()
    trees = [grow_blocks(coordinates(drawn["p"][drawn["_g"] == g])) for g in range(len(big))]
    boxes = [(np.array([lo for lo, _ in b]), np.array([hi for _, hi in b])) for _, b in trees]

    def deal(batches):
        for pdf in batches:
            out = np.zeros(len(pdf), np.int64)
            for g in pdf["_g"].unique():
                if g < 0:
                    continue
                at = np.flatnonzero(pdf["_g"].to_numpy() == g)
                out[at] = blocks_of(coordinates(pdf["p"].iloc[at]), trees[int(g)][0])
            yield pdf.assign(_b=out)

    def ask(batches):
        """The points with every other block that may hold a nearer one."""
        for pdf in batches:
            parts = []
            for g in pdf["_g"].unique():
                at = np.flatnonzero(pdf["_g"].to_numpy() == g)
                for a in range(0, len(at), ROWS * 4):
                    part = pdf.iloc[at[a : a + ROWS * 4]]
                    x = coordinates(part["p"])[:, None, :]
                    away = gaps(x, x, *(v[None] for v in boxes[int(g)]))
                    away[np.arange(len(part)), part["_b"].to_numpy()] = np.inf
                    row, to = np.nonzero((away <= part["far"].to_numpy()[:, None]) & (away < np.inf))
                    parts.append(part.iloc[row].assign(_b=to))
            yield pd.concat(parts) if parts else pdf

    def answer(pdf: pd.DataFrame) -> pd.DataFrame:
        asks = pdf["far"].notna().to_numpy()
        x, ids = coordinates(pdf["p"]), pdf["id"].to_numpy()
        row, rank, other, d2 = tree_nearest(x[asks], x[~asks], ids[~asks], k, pdf["far"].to_numpy(float)[asks])
        return pd.DataFrame({"id": ids[asks][row], "rank": rank, "other": other, "d2": d2})

    dealt = p.mapInPandas(deal, T.StructType([*p.schema.fields, T.StructField("_b", T.LongType())]))
    local = materialize(dealt.repartition(tasks, *keys, "_b").groupBy(*keys, "_b").applyInPandas(own, f"{graph}, p array<double>, _g int, _b long, far double"))
    asking = local.where("rank = 0").select("id", "p", "_g", "_b", "far")
    cut_points = asking.withColumn("far", F.lit(None).cast("double"))
    met = cut_points.unionByName(asking.mapInPandas(ask, cut_points.schema)).repartition(tasks, "_g", "_b").groupBy("_g", "_b").applyInPandas(answer, graph)
    best = Window.partitionBy("id").orderBy("d2", "other")
    found = local.where("rank > 0").select("id", "rank", "other", "d2").unionByName(met)
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("id", "rank", "other", "d2")


def _all_pairs_graph(p: DataFrame, k: int, keys: list[str]) -> DataFrame:
    """proximity_graph() by all pairs: every chunk of a drawing's points meets every other one as arrays, which keeps k of a chunk."""
    p = materialize(p)
    sizes = p.groupBy(*keys).agg(F.ceil(F.count("*") / COLUMNS).alias("_chunks"))
    p = p.join(sizes, keys).withColumn("_c", F.pmod(F.xxhash64("id"), F.col("_chunks")))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.col("_chunks") - 1))
    sides = p.select("id", "p", *keys, F.lit(True).alias("_asks"), F.col("_c").alias("_x"), every.alias("_y")).unionByName(p.select("id", "p", *keys, F.lit(False).alias("_asks"), every.alias("_x"), F.col("_c").alias("_y")))

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        asks = pdf["_asks"].to_numpy()
        held = pdf[~asks].sort_values("id")
        ids, x = pdf["id"].to_numpy()[asks], coordinates(pdf["p"][asks])
        c_ids, c = held["id"].to_numpy(), coordinates(held["p"])
        parts = []
        for a in range(0, len(ids) if len(c) else 0, ROWS):
            d2 = distances(x[a : a + ROWS], c)
            d2[ids[a : a + ROWS, None] == c_ids] = np.inf
            row, far, other = least(d2, c_ids, k)
            parts.append(pd.DataFrame({"id": ids[a + row], "other": other, "d2": far}))
        return pd.concat(parts) if parts else pd.DataFrame({"id": ids[:0], "other": ids[:0], "d2": np.zeros(0)})

    tasks = int(p.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = sides.repartition(tasks, *keys, "_x", "_y").groupBy(*keys, "_x", "_y").applyInPandas(meet, "id {id}, other {id}, d2 double".format(id=p.schema["id"].dataType.simpleString()))
    best = Window.partitionBy("id").orderBy("d2", "other")
    return met.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("id", "rank", "other", "d2")


def proximity_graph(points: DataFrame, k: int = 10, method: str = "buckets", width: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """(id, rank, other, d2) of the k nearest of each 4-D point p by (squared distance, id), among points that agree in the columns by.

    buckets: blocks of a tree of cuts in 4-D, searched by a tree of their own each; a point asks other blocks only where its k-th
    neighbour leaves room for nearer ones, so two rounds settle all, wherever they lie. all_pairs: the baseline, every point of a drawing
    with every other. width: without effect, as blocks follow the points; it stays for callers that name it. Points without four
    finite coordinates or without a drawing have no neighbours.
    """
    keys = list(by) or ["_all"]
    p = (points if by else points.withColumn("_all", F.lit(0))).select("id", F.transform("p", lambda v: v.cast("double")).alias("p"), *keys)
    p = p.where(reduce(lambda a, c: a & c, [F.col(c).isNotNull() for c in keys], F.forall("p", lambda v: F.abs(v) < float("inf")) & (F.size("p") == 4)))
    return (_all_pairs_graph if method == "all_pairs" else _tree_graph)(p, k, keys)


def bundle_ink(edges: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(ink, meeting points) of edges (x1, y1, x2, y2) drawn together: from every source to one meeting point, along, and out to every
    target. The meeting points slide along the axis between the mean ends; golden-section search finds the cheapest pair."""
    a, b = edges[:, :2].mean(0), edges[:, 2:].mean(0)

    def ink(t: float) -> float:
        m1, m2 = a + (b - a) * t, b + (a - b) * t
        return float(np.hypot(*(edges[:, :2] - m1).T).sum() + np.hypot(*(edges[:, 2:] - m2).T).sum() + np.hypot(*(m2 - m1)))

    lo, hi = 0.0, 0.5
    for _ in range(30):
        x, y = hi - GOLDEN * (hi - lo), lo + GOLDEN * (hi - lo)
        if ink(x) < ink(y):
            hi = y
        else:
            lo = x
    t = (lo + hi) / 2
    return ink(t), a + (b - a) * t, b + (a - b) * t


def straight_ink(edges: np.ndarray) -> float:
    return float(np.hypot(edges[:, 2] - edges[:, 0], edges[:, 3] - edges[:, 1]).sum())


def group_ink(edges: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """bundle_ink() of many groups of edges at once; starts: where each group's rows begin."""
    size = np.diff(np.append(starts, len(edges)))
    mean = np.add.reduceat(edges, starts) / size[:, None]
    a, b = mean[:, :2], mean[:, 2:]
    of = np.repeat(np.arange(len(starts)), size)

    def ink(t: np.ndarray) -> np.ndarray:
        m1, m2 = a + (b - a) * t[:, None], b + (a - b) * t[:, None]
        each = np.hypot(*(edges[:, :2] - m1[of]).T) + np.hypot(*(edges[:, 2:] - m2[of]).T)
        return np.add.reduceat(each, starts) + np.hypot(*(m2 - m1).T)

    lo, hi = np.zeros(len(starts)), np.full(len(starts), 0.5)
    for _ in range(30):
        x, y = hi - GOLDEN * (hi - lo), lo + GOLDEN * (hi - lo)
        less = ink(x) < ink(y)
        lo, hi = np.where(less, lo, x), np.where(less, y, hi)
    return ink((lo + hi) / 2)


#: Rows that one call of group_ink() prices at a time, which bounds its memory.
PRICED_ROWS = 1 << 20


def coalesce(edges: np.ndarray, near: list, max_angle: float = 60.0) -> tuple[np.ndarray, np.ndarray]:
    """(bundle of every edge, ink of its bundle). Rounds of mutually best merges between proximity neighbours until none saves ink.

    near: the proximity neighbours of every edge. Edges are never compared beyond them, and a pair of bundles is priced again only
    after one of the two has grown; all pairs of a round are priced together.
    """
    n = len(edges)
    label = np.arange(n)
    cost = np.hypot(edges[:, 2] - edges[:, 0], edges[:, 3] - edges[:, 1]) if n else np.zeros(0)
    i = np.repeat(np.arange(n), [len(v) for v in near])
    j = np.fromiter((o for v in near for o in v), np.int64, len(i))
    direction = np.arctan2(edges[:, 3] - edges[:, 1], edges[:, 2] - edges[:, 0])
    turn = np.abs((direction[i] - direction[j] + math.pi) % (2 * math.pi) - math.pi)
    pairs = np.unique(np.stack([np.minimum(i, j), np.maximum(i, j)], 1)[np.degrees(turn) <= max_angle], axis=0)
    known, saved, grown = np.zeros(0, np.int64), np.zeros(0), np.zeros(n, bool)

    def price(g: np.ndarray, h: np.ndarray, members: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
        out = np.empty(len(g))
        rows = size[g] + size[h]
        lot = 0
        while lot < len(g):
            end = max(lot + 1, lot + int(np.searchsorted(np.cumsum(rows[lot:]), PRICED_ROWS, "right")))
            ends = np.stack([first[g[lot:end]], first[h[lot:end]]], 1).ravel()
            many = np.stack([size[g[lot:end]], size[h[lot:end]]], 1).ravel()
            at = np.repeat(ends - np.cumsum(many) + many, many) + np.arange(many.sum())
            starts = np.concatenate([[0], np.cumsum(rows[lot : end - 1])])
            out[lot:end] = cost[g[lot:end]] + cost[h[lot:end]] - group_ink(edges[members[at]], starts)
            lot = end
        return out

    while len(pairs):
        g, h = label[pairs[:, 0]], label[pairs[:, 1]]
        pairs = pairs[g != h]
        key = np.unique(np.minimum(g, h)[g != h] * n + np.maximum(g, h)[g != h])
        g, h = key // n, key % n
        members = np.argsort(label, kind="stable")
        size = np.bincount(label, minlength=n)
        first = np.concatenate([[0], np.cumsum(size)[:-1]])
        at = np.minimum(np.searchsorted(known, key), max(0, len(known) - 1))
        held = (known[at] == key) & ~grown[g] & ~grown[h] if len(known) else np.zeros(len(key), bool)
        now = np.empty(len(key))
        now[held] = saved[at[held]] if len(known) else 0.0
        now[~held] = price(g[~held], h[~held], members, first, size)
        known, saved = key, now
        # each bundle wishes for the partner that saves most, of equals the first; mutual wishes come true
        use = now > 1e-9
        x, y, s = np.concatenate([g[use], h[use]]), np.concatenate([h[use], g[use]]), np.tile(now[use], 2)
        order = np.lexsort((y, -s, x))
        lead = order[np.flatnonzero(np.concatenate([[True], x[order][1:] != x[order][:-1]]))] if len(order) else order
        wish = np.full(n, -1)
        wish[x[lead]] = y[lead]
        merge = np.flatnonzero((wish >= 0) & (wish[np.maximum(wish, 0)] == np.arange(n)) & (np.arange(n) < wish))
        if not len(merge):
            break
        gone = wish[merge]
        gain = saved[np.searchsorted(known, merge * n + gone)]
        cost[merge] = cost[merge] + cost[gone] - gain
        to = np.arange(n)
        to[gone] = merge
        label = to[label]
        grown = np.zeros(n, bool)
        grown[merge] = True
    return label, cost[label]


def bundle(edges: DataFrame, knn: int = 10, max_angle: float = 60.0, by: tuple[str, ...] = ("level",)) -> DataFrame:
    """Edges (id, by..., x1, y1, x2, y2) with their bundle, the ink of the bundle and their own straight ink. What agrees in the columns
    by is one drawing: a level, or a level and a tile, which spreads a level over tasks and keeps a task's share at what a view shows.

    Neighbours come from the distributed proximity_graph() over the ends, scaled by their spread in the drawing, so no edge meets all
    others; the merges of a drawing depend on one another and run in one task. Edges of no length draw nothing and stay alone.
    """
    ends = ["x1", "y1", "x2", "y2"]
    length = F.hypot(F.col("x2") - F.col("x1"), F.col("y2") - F.col("y1"))
    lines = materialize(edges.where(length > 0))
    spread = lines.groupBy(*by).agg(*[F.avg(c).alias(f"_m{c}") for c in ends], *[F.greatest(F.stddev_pop(c), F.lit(1e-3)).alias(f"_s{c}") for c in ends])
    scaled = lines.join(spread, list(by)).select("id", *by, F.array(*[(F.col(c) - F.col(f"_m{c}")) / F.col(f"_s{c}") for c in ends]).alias("p"))
    near = proximity_graph(scaled, knn, by=by).groupBy("id").agg(F.transform(F.sort_array(F.collect_list(F.struct("rank", "other"))), lambda n: n["other"]).alias("_near"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id").reset_index(drop=True)
        ids, e = pdf["id"].to_numpy(), pdf[ends].to_numpy(float)
        label, ink = coalesce(e, [np.searchsorted(ids, [] if n is None else n) for n in pdf["_near"]], max_angle)
        return pdf.drop(columns="_near").assign(bundle=ids[label], bundle_ink=ink, straight_ink=np.hypot(e[:, 2] - e[:, 0], e[:, 3] - e[:, 1]))

    added = [T.StructField("bundle", T.LongType()), T.StructField("bundle_ink", T.DoubleType()), T.StructField("straight_ink", T.DoubleType())]
    out = lines.join(near, "id", "left").select(*edges.columns, "_near").groupBy(*by).applyInPandas(run, T.StructType([*edges.schema.fields, *added]))
    return out.unionByName(edges.where(length == 0).withColumns({"bundle": F.col("id"), "bundle_ink": F.lit(0.0), "straight_ink": F.lit(0.0)}))
