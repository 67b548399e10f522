"""Building blocks of the oracle SQL: named sub-queries over the given tables, put together by with_()."""

from __future__ import annotations

LEVELS = "SELECT CAST(unnest(range(1, 11)) AS INTEGER) AS level"

BLOCKS: dict[str, tuple[tuple[str, ...], str]] = {
    "seed": ((), """SELECT *, CAST(round(value * 100) AS BIGINT) AS s, (event_id * 1103515245 + 12345) % 2147483648 AS ra,
        (event_id * 214013 + 2531011) % 2147483647 AS rb, (user_id * 48271 + 11) % 2147483647 AS u FROM events"""),
    "anchored": (("seed",), """SELECT *, CASE WHEN (rb // 7) % 8 = 0 THEN (rb // 64) % 100 ELSE u % 100 END AS q FROM seed"""),
    "pts": (("anchored",), """SELECT event_id AS point_id, user_id, ts, event_type, value, props,
        greatest(least(((7 * i + 3) % 26) * 15360000 + ((5381 * i) % 15360) * 1000 + (s * ((ra // 128) % 2001)) // 8 - 125 * s, 399359999), 0) AS x_mas,
        greatest(least(((11 * i + 5) % 18) * 15360000 + ((7919 * i) % 15360) * 1000 + (s * ((rb // 128) % 2001)) // 8 - 125 * s, 276479999), 0) AS y_mas
        FROM (SELECT *, (q * q) // 400 AS i FROM anchored)"""),
    "mv0": (("pts",), """SELECT * FROM (SELECT point_id AS movement_id, user_id, ts AS t0, lead(ts) OVER w AS t1, x_mas AS sx, y_mas AS sy,
        lead(x_mas) OVER w AS tx, lead(y_mas) OVER w AS ty, event_type, value FROM pts WINDOW w AS (PARTITION BY user_id ORDER BY ts, point_id)) WHERE t1 IS NOT NULL"""),
    "mv": (("mv0",), """SELECT *, 2 * 6371.0088 * asin(sqrt(pow(sin((radians(7 + ty / 3.6e6) - radians(7 + sy / 3.6e6)) / 2), 2)
        + cos(radians(7 + sy / 3.6e6)) * cos(radians(7 + ty / 3.6e6)) * pow(sin((radians(-168 + tx / 3.6e6) - radians(-168 + sx / 3.6e6)) / 2), 2))) AS dist_km,
        (epoch_us(t1) - epoch_us(t0)) // 1000000 AS travel_s FROM mv0"""),
    "lv": ((), LEVELS),
    "capped": (("lv",), "SELECT level, 32.0 * (1 << (level - 1)) AS cap FROM lv"),
    "ends": (("mv",), "SELECT movement_id, user_id, t0, t1, travel_s, dist_km, sx AS x, sy AS y FROM mv UNION ALL SELECT movement_id, user_id, t0, t1, travel_s, dist_km, tx, ty FROM mv"),
    "wide": (("ends", "lv"), "SELECT level, (x // 30000) >> (level - 1) AS cx, (y // 30000) >> (level - 1) AS cy, * EXCLUDE (level) FROM ends, lv"),
    "nodes": (("wide",), "SELECT level, cx, cy, count(*) AS n, CAST(sum(x) AS BIGINT) AS sum_x, CAST(sum(y) AS BIGINT) AS sum_y FROM wide GROUP BY level, cx, cy"),
    "flows": (("mv", "capped"), """SELECT level, (sx // 30000) >> (level - 1) AS sx, (sy // 30000) >> (level - 1) AS sy, (tx // 30000) >> (level - 1) AS tx, (ty // 30000) >> (level - 1) AS ty,
        t0, t1, user_id, travel_s, dist_km, cap, event_type FROM mv, capped"""),
    "edges": (("flows",), "SELECT level, sx, sy, tx, ty, count(*) AS n FROM flows WHERE dist_km < cap GROUP BY ALL"),
    "disc": ((), "SELECT a.i AS dx, b.i AS dy FROM (SELECT unnest(range(-6, 7)) AS i) a, (SELECT unnest(range(-6, 7)) AS i) b"),
    "around": (("nodes", "disc"), "SELECT p.level, p.cx, p.cy, p.n, q.n AS qn, dx, dy FROM nodes p, disc d, nodes q WHERE q.level = p.level AND q.cx = p.cx + dx AND q.cy = p.cy + dy"),
    "near": (("nodes", "disc"), "SELECT p.level, p.cx, p.cy, p.n, q.n AS qn FROM nodes p JOIN disc d ON dx * dx + dy * dy < 9 JOIN nodes q ON q.level = p.level AND q.cx = p.cx + dx AND q.cy = p.cy + dy"),
    "scores": (("near",), """SELECT level, cx, cy, n, count(*) AS neighbours, CAST(count(*) FILTER (qn <= n) AS DOUBLE) / count(*) AS rank_weak,
        CAST(count(*) FILTER (qn < n) AS DOUBLE) / count(*) AS rank_strict, (CAST(count(*) FILTER (qn <= n) AS DOUBLE) + count(*) FILTER (qn < n)) / 2 / count(*) AS rank_mean,
        CASE WHEN count(*) > 1 THEN CAST(count(*) FILTER (qn < n) AS DOUBLE) / (count(*) - 1) ELSE 0.0 END AS rank_relative FROM near GROUP BY level, cx, cy, n"""),
    "kept": (("scores",), "SELECT level, cx, cy, n FROM scores WHERE rank_weak > 0.8"),
    "kedges": (("edges", "kept"), """SELECT e.* FROM edges e WHERE EXISTS (SELECT 1 FROM kept k WHERE k.level = e.level AND k.cx = e.sx AND k.cy = e.sy)
        AND EXISTS (SELECT 1 FROM kept k WHERE k.level = e.level AND k.cx = e.tx AND k.cy = e.ty)"""),
    "dims": (("kept",), "SELECT level, count(*) AS kept, CAST(ceil(-count(*) * ln(0.01) / pow(ln(2), 2)) AS BIGINT) AS m FROM kept GROUP BY level"),
    "dimk": (("dims",), "SELECT level, kept, m, CAST(greatest(1, round(m / kept * ln(2))) AS INTEGER) AS k FROM dims"),
    "bits": (("kept", "dimk"), """SELECT DISTINCT d.level, ((((cx << 14) | cy) * 2654435761 + 97) % 2147483647 + i * ((((cx << 14) | cy) * 40503 + 12345) % 2147483647 + 1)) % m AS pos
        FROM kept JOIN dimk d USING (level), (SELECT unnest(range(0, 32)) AS i) WHERE i < d.k"""),
    "probe": (("nodes", "dimk", "bits"), """SELECT level, cx, cy FROM (SELECT n.level, n.cx, n.cy, d.k, ((((cx << 14) | cy) * 2654435761 + 97) % 2147483647 + i * ((((cx << 14) | cy) * 40503 + 12345) % 2147483647 + 1)) % m AS pos
        FROM nodes n JOIN dimk d USING (level), (SELECT unnest(range(0, 32)) AS i) WHERE i < d.k) p JOIN bits b USING (level, pos) GROUP BY level, cx, cy, k HAVING count(*) = k"""),
    "bedges": (("edges", "probe"), """SELECT e.* FROM edges e WHERE EXISTS (SELECT 1 FROM probe k WHERE k.level = e.level AND k.cx = e.sx AND k.cy = e.sy)
        AND EXISTS (SELECT 1 FROM probe k WHERE k.level = e.level AND k.cx = e.tx AND k.cy = e.ty)"""),
    "shipseed": ((), """SELECT o_custkey AS user_id, o_orderdate AS t0, l_shipdate AS t1, l_returnflag, l_extendedprice, o_orderpriority, c_mktsegment, s_nationkey, c_nationkey,
        CAST(round((s_acctbal + 1000) * 100) AS BIGINT) // 64 AS s1, CAST(round((c_acctbal + 1000) * 100) AS BIGINT) // 64 AS s2,
        (s_suppkey * 1103515245 + 12345) % 2147483648 AS a1, (s_suppkey * 214013 + 2531011) % 2147483647 AS b1, (c_custkey * 1103515245 + 12345) % 2147483648 AS a2, (c_custkey * 214013 + 2531011) % 2147483647 AS b2
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey"""),
    "ships": (("shipseed",), """SELECT * EXCLUDE (s1, s2, a1, b1, a2, b2),
        greatest(least(((7 * s_nationkey + 3) % 26) * 15360000 + ((5381 * s_nationkey) % 15360) * 1000 + (s1 * ((a1 // 128) % 2001)) // 8 - 125 * s1, 399359999), 0) AS sx,
        greatest(least(((11 * s_nationkey + 5) % 18) * 15360000 + ((7919 * s_nationkey) % 15360) * 1000 + (s1 * ((b1 // 128) % 2001)) // 8 - 125 * s1, 276479999), 0) AS sy,
        greatest(least(((7 * c_nationkey + 3) % 26) * 15360000 + ((5381 * c_nationkey) % 15360) * 1000 + (s2 * ((a2 // 128) % 2001)) // 8 - 125 * s2, 399359999), 0) AS tx,
        greatest(least(((11 * c_nationkey + 5) % 18) * 15360000 + ((7919 * c_nationkey) % 15360) * 1000 + (s2 * ((b2 // 128) % 2001)) // 8 - 125 * s2, 276479999), 0) AS ty FROM shipseed"""),
    "popview": (("pts",), """SELECT set_id, CAST(row_number() OVER (PARTITION BY set_id ORDER BY h, point_id) - 1 AS INTEGER) AS query_id, CAST(1 + h % 10 AS INTEGER) AS level, x_mas, y_mas
        FROM (SELECT set_id, point_id, x_mas, y_mas, (point_id * 69621 + 7919 * set_id) % 2147483647 AS h FROM pts, (SELECT unnest([0, 1, 2]) AS set_id))"""),
    "views": (("popview",), """SELECT CAST(set_id AS INTEGER) AS set_id, query_id, greatest(x_mas - 16 * (30000 << (level - 1)), 0) AS x0, greatest(y_mas - 9 * (30000 << (level - 1)), 0) AS y0,
        least(x_mas + 16 * (30000 << (level - 1)), 399360000) AS x1, least(y_mas + 9 * (30000 << (level - 1)), 276480000) AS y1, level FROM popview WHERE query_id < 2000"""),
}


def with_(names: str, select: str, mv_from: str = "mv0") -> str:
    """A SELECT over the named blocks and whatever they need, in order. mv_from: what the movements are taken from."""
    need: list[str] = []
    blocks = dict(BLOCKS)
    if mv_from == "ships":
        blocks["mv"] = (("ships",), blocks["mv"][1].replace("FROM mv0", "FROM (SELECT *, 1 AS movement_id, '' AS event_type FROM ships)"))
    elif mv_from != "mv0":
        blocks["mv"] = (("mv0",), blocks["mv"][1].replace("FROM mv0", f"FROM {mv_from}"))

    def add(name: str) -> None:
        for d in blocks[name][0]:
            add(d)
        if name not in need:
            need.append(name)

    for n in names.split():
        add(n)
    # blocks that several others read are computed once
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({blocks[n][1]})" for n in need) + "\n" + select


def bisection(points: str, k: int, axis: str = "best", out: str = "leaves") -> str:
    """Sub-queries that end in out(leaf, x0, y0, x1, y1, path): a region cut into k rectangles of like weight, depth by depth.

    points: a SELECT of x, y, w. Every depth lists the cuts between distinct values of each box and axis, takes the one that comes
    nearest to its share of the weight (the first of equals), then the axis with the smaller miss (x of equals); alternate asks
    the depth's own axis first.
    """
    parts, depth, widest = [f"{out}_0 AS MATERIALIZED (SELECT x, y, w, '' AS path, CAST({k} AS BIGINT) AS want, 0::BIGINT AS x0, 0::BIGINT AS y0, 399360000::BIGINT AS x1, 276480000::BIGINT AS y1 FROM ({points}))"], 0, k
    while widest > 1:
        p, c = f"{out}_{depth}", f"{out}_cut_{depth}"
        first = "a" if axis == "best" else f"CASE WHEN a = {depth % 2} THEN 0 ELSE 1 END"
        order = f"miss / total, {first}" if axis == "best" else f"{first}, miss / total"
        parts.append(f"""{c} AS MATERIALIZED (SELECT path, a, pos FROM (SELECT *, row_number() OVER (PARTITION BY path ORDER BY {order}) AS best FROM (
            SELECT *, row_number() OVER (PARTITION BY path, a ORDER BY miss, v) AS nearest FROM (
              SELECT path, a, v, lead(v) OVER o AS pos, abs(sum(c) OVER o - (CAST(want // 2 AS DOUBLE) / want) * sum(c) OVER (PARTITION BY path, a)) AS miss, sum(c) OVER (PARTITION BY path, a) AS total FROM (
                SELECT path, want, 0 AS a, x AS v, CAST(sum(w) AS DOUBLE) AS c FROM {p} WHERE want > 1 GROUP BY ALL UNION ALL SELECT path, want, 1, y, CAST(sum(w) AS DOUBLE) FROM {p} WHERE want > 1 GROUP BY ALL)
              WINDOW o AS (PARTITION BY path, a ORDER BY v)) WHERE pos IS NOT NULL) WHERE nearest = 1) WHERE best = 1)""")
        low = "CASE WHEN a = 0 THEN x < pos ELSE y < pos END"
        parts.append(f"""{out}_{depth + 1} AS MATERIALIZED (SELECT x, y, w, CASE WHEN pos IS NULL THEN path WHEN low THEN path || '0' ELSE path || '1' END AS path, CASE WHEN pos IS NULL THEN want WHEN low THEN want // 2 ELSE want - want // 2 END AS want,
            CASE WHEN a = 0 AND NOT low THEN pos ELSE x0 END AS x0, CASE WHEN a = 1 AND NOT low THEN pos ELSE y0 END AS y0, CASE WHEN a = 0 AND low THEN pos ELSE x1 END AS x1, CASE WHEN a = 1 AND low THEN pos ELSE y1 END AS y1
            FROM (SELECT p.*, a, pos, {low} AS low FROM {p} p LEFT JOIN {c} c ON p.path = c.path))""")
        depth, widest = depth + 1, widest - widest // 2
    parts.append(f"{out} AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY path) - 1 AS INTEGER) AS leaf, x0, y0, x1, y1 FROM (SELECT DISTINCT path, x0, y0, x1, y1 FROM {out}_{depth}))")
    return ",\n".join(parts)


#: Constants of the 32-bit mixing hash by which Spark deals rows to partitions.
_MASK, _C1, _C2, _MUL, _ADD, _F1, _F2 = 0xFFFFFFFF, 0xCC9E2D51, 0x1B873593, 5, 0xE6546B64, 0x85EBCA6B, 0xC2B2AE35


def hash_partition(level: str, cx: str, cy: str, k: int) -> tuple[list[str], str]:
    """Sub-selects, each over the one before, and the last column: pmod(hash(level, cx, cy), k) for an int and two longs."""
    rot = lambda v, n: f"((({v} << {n}) | ({v} >> {32 - n})) & {_MASK})"
    mul = lambda v, c: f"(CAST(({v})::HUGEINT * {c} % 4294967296 AS BIGINT))"
    steps: list[str] = ["42::BIGINT AS h"]

    def word(v: str) -> None:
        steps.append(f"{mul(f'(({v}) & {_MASK})', _C1)} AS q")
        steps.append(f"{mul(rot('q', 15), _C2)} AS q")
        steps.append("xor(h, q) AS h")
        steps.append(f"({rot('h', 13)} * {_MUL} + {_ADD}) & {_MASK} AS h")

    def final(length: int) -> None:
        steps.append(f"xor(h, {length}) AS h")
        for shift, c in ((16, _F1), (13, _F2)):
            steps.append(f"xor(h, h >> {shift}) AS h")
            steps.append(f"{mul('h', c)} AS h")
        steps.append("xor(h, h >> 16) AS h")

    word(f"CAST({level} AS BIGINT)")
    final(4)
    for v in (cx, cy):
        word(f"CAST({v} AS BIGINT)")
        word(f"CAST({v} AS BIGINT) >> 32")
        final(8)
    signed = "CASE WHEN h >= 2147483648 THEN h - 4294967296 ELSE h END"
    return steps, f"(({signed}) % {k} + {k}) % {k}"


def hash_placed(source: str, k: int) -> str:
    """SELECT of the rows of source (level, cx, cy, ...) with slot, their hash partition of k."""
    steps, slot = hash_partition("level", "cx", "cy", k)
    out = source
    for i, step in enumerate(steps):
        name = step.rsplit(" AS ", 1)[1]
        keep = "* EXCLUDE (h)" if name == "h" and i else "* EXCLUDE (q)" if name == "q" and i > 1 else "*"
        out = f"(SELECT {keep}, {step} FROM {out})"
    return f"(SELECT *, {slot} AS slot FROM {out})"
