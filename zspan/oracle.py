"""DuckDB SQL of the same results, from the tables on: no array, no shared code."""

from __future__ import annotations

from zspan.workloads.windows import SELECTIVITIES

LEAF_CAP = 64


def z(x: str, y: str) -> str:
    """Interleaved bits, one term a bit."""
    terms = [f"(({x} & {1 << k}) << {k})" for k in range(30)] + [f"(({y} & {1 << k}) << {k + 1})" for k in range(29)]
    return "(" + " | ".join(terms) + ")"


_ROADS = """
    SELECT o_orderkey AS geom_id, 'LINESTRING' AS kind, 0 AS ring,
        row_number() OVER (PARTITION BY o_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS ord,
        (c_nationkey % 5) * 144000000 + 72000000 + ((o_orderkey * 7919) % 4001 - 2000) * (1 + o_custkey % 10) * 1000 + (l_partkey % 200) * 500 * CASE WHEN o_orderkey % 100 = 0 THEN 200 ELSE 1 END AS x,
        (c_nationkey // 5) * 72000000 + 36000000 + ((o_orderkey * 104729) % 4001 - 2000) * (1 + o_custkey % 10) * 1000 + (l_suppkey % 100) * 500 * CASE WHEN o_orderkey % 100 = 0 THEN 200 ELSE 1 END AS y
    FROM orders JOIN customer ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey"""
_WATER = """
    SELECT user_id * 100 + day(ts) AS geom_id, 'LINESTRING' AS kind, 0 AS ring,
        row_number() OVER (PARTITION BY user_id * 100 + day(ts) ORDER BY ts, event_id) AS ord,
        ((user_id * 7919) % 700) * 1000000 + CAST(round(value * 100) AS BIGINT) * 100 AS x,
        ((user_id * 104729) % 350) * 1000000 + CAST(regexp_extract(props, '(\\d+)', 1) AS BIGINT) * 10000 AS y
    FROM events"""
_PARKS = """
    SELECT p_partkey AS geom_id, 'POLYGON' AS kind, c.ring, c.ord,
        CAST(regexp_extract(p_brand, '(\\d+)', 1) AS BIGINT) * 26000000 + ((p_partkey * 7919) % 4001) * 4000 + c.a * s // 4 AS x,
        ((p_partkey * 104729) % 4001) * 40000 + 50000000 + c.b * s // 4 AS y
    FROM (SELECT *, CAST(p_size AS BIGINT) * 2000 * CASE WHEN p_partkey % 100 = 0 THEN 100 ELSE 1 END AS s FROM part)
    JOIN (VALUES ('L', 0, 1, 0, 0), ('L', 0, 2, 8, 0), ('L', 0, 3, 8, 4), ('L', 0, 4, 4, 4), ('L', 0, 5, 4, 8), ('L', 0, 6, 0, 8), ('L', 0, 7, 0, 0),
                 ('T', 0, 1, 0, 0), ('T', 0, 2, 8, 0), ('T', 0, 3, 0, 8), ('T', 0, 4, 0, 0),
                 ('H', 1, 1, 1, 1), ('H', 1, 2, 3, 1), ('H', 1, 3, 3, 3), ('H', 1, 4, 1, 3), ('H', 1, 5, 1, 1)) AS c(shape, ring, ord, a, b)
    ON c.shape = CASE WHEN p_partkey % 11 = 0 THEN 'T' ELSE 'L' END OR (c.shape = 'H' AND p_partkey % 7 = 0)"""
_POINTS = """
    SELECT vec_id AS geom_id, 'POINT' AS kind, 0 AS ring, 1 AS ord,
        CAST(least(greatest(floor((CAST(embedding[1] AS DOUBLE) + 1) * 360000000), 0), 719999999) AS BIGINT) AS x,
        CAST(least(greatest(floor((CAST(embedding[2] AS DOUBLE) + 1) * 180000000), 0), 359999999) AS BIGINT) AS y
    FROM embeddings"""
_VERTS = {"roads": _ROADS, "water": _WATER, "parks": _PARKS, "points": _POINTS}


def geoms(name: str) -> str:
    """CTEs verts, segs and boxes."""
    return f"""verts AS (SELECT geom_id, kind, ring, ord, CAST(x AS BIGINT) AS x, CAST(y AS BIGINT) AS y FROM ({_VERTS[name]})),
    segs AS (SELECT * FROM (
        SELECT geom_id, x AS ax, y AS ay, coalesce(lead(x) OVER w, CASE WHEN count(*) OVER g = 1 THEN x END) AS bx, coalesce(lead(y) OVER w, CASE WHEN count(*) OVER g = 1 THEN y END) AS ey
        FROM verts WINDOW w AS (PARTITION BY geom_id, ring ORDER BY ord), g AS (PARTITION BY geom_id, ring)) WHERE bx IS NOT NULL),
    boxed AS (SELECT geom_id, min(x) AS x0, min(y) AS y0, max(x) AS x1, max(y) AS y1 FROM verts GROUP BY geom_id),
    coded AS (SELECT *, {z('x0', 'y0')} AS zmin, {z('x1', 'y1')} AS zmax FROM boxed),
    boxes AS (SELECT *, zmax - zmin AS zlen FROM coded)"""


def windows(sel: str) -> str:
    """CTE windows, with intervals, after ``geoms``."""
    num, den = SELECTIVITIES[sel]
    return f"""n AS (SELECT count(*) AS n, greatest(1, (count(*) * {num} + {den} - 1) // {den}) AS k FROM boxes),
    numbered AS (SELECT *, row_number() OVER (ORDER BY geom_id) - 1 AS rn FROM boxes),
    seeds AS (SELECT i AS qid, x0 AS sx0, y0 AS sy0, x1 AS sx1, y1 AS sy1 FROM range(100) r(i), n JOIN numbered ON rn = i * n.n // 100),
    far AS (SELECT qid, b.*, greatest(0, sx0 - x1, x0 - sx1) AS dx, greatest(0, sy0 - y1, y0 - sy1) AS dy FROM seeds, boxes b),
    near AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dx * dx + dy * dy, geom_id) AS r FROM far),
    w0 AS (SELECT qid, min(x0) AS wx0, max(x1) AS wx1, min(y0) AS wy0, max(y1) AS wy1 FROM near, n WHERE r <= k GROUP BY qid),
    windows AS (SELECT *, {z('wx0', 'wy0')} AS zlo, {z('wx1', 'wy1')} AS zhi FROM w0)"""


TILES = f"""w0 AS (SELECT n_nationkey AS qid, CAST((n_nationkey % 5) * 144000000 AS BIGINT) AS wx0, CAST((n_nationkey % 5 + 1) * 144000000 AS BIGINT) AS wx1,
        CAST((n_nationkey // 5) * 72000000 AS BIGINT) AS wy0, CAST((n_nationkey // 5 + 1) * 72000000 AS BIGINT) AS wy1 FROM nation),
    windows AS (SELECT CAST(qid AS BIGINT) AS qid, wx0, wx1, wy0, wy1, {z('wx0', 'wy0')} AS zlo, {z('wx1', 'wy1')} AS zhi FROM w0)"""
_MEET = "b.x0 <= w.wx1 AND b.x1 >= w.wx0 AND b.y0 <= w.wy1 AND b.y1 >= w.wy0"


def _side(x: str, y: str) -> str:
    return f"((bx - ax) * ({y} - ay) - (ey - ay) * ({x} - ax))"


def results(name: str, rel: str) -> str:
    """CTE hits (qid, geom_id), after ``geoms`` and windows."""
    if rel == "contains":
        inside = "FROM windows w JOIN boxes b ON w.wx0 < w.wx1 AND w.wy0 < w.wy1 AND b.x0 >= w.wx0 AND b.x1 <= w.wx1 AND b.y0 >= w.wy0 AND b.y1 <= w.wy1"
        if name == "parks":
            return f"hits AS (SELECT qid, geom_id {inside})"
        return f"""hits AS (SELECT qid, geom_id {inside} JOIN segs s USING (geom_id) GROUP BY qid, geom_id
            HAVING bool_or(NOT ((ax = bx AND (ax = wx0 OR ax = wx1)) OR (ay = ey AND (ay = wy0 OR ay = wy1)))))"""
    corners = [_side(x, y) for x in ("wx0", "wx1") for y in ("wy0", "wy1")]
    meets = f"(least(ax, bx) <= wx1 AND greatest(ax, bx) >= wx0 AND least(ay, ey) <= wy1 AND greatest(ay, ey) >= wy0 AND least({', '.join(corners)}) <= 0 AND greatest({', '.join(corners)}) >= 0)"
    parity = f"sum(CASE WHEN (ay > wy0) <> (ey > wy0) AND ({_side('wx0', 'wy0')} > 0) = (ey > ay) THEN 1 ELSE 0 END) % 2 = 1"
    return f"hits AS (SELECT qid, geom_id FROM windows w JOIN boxes b ON {_MEET} JOIN segs s USING (geom_id) GROUP BY qid, geom_id HAVING bool_or({meets})" + (f" OR {parity}" if name == "parks" else "") + ")"


def stores(q: str = "0.99", m: str = "greatest(1, n // 1000)", cap: int = LEAF_CAP) -> str:
    """CTEs limit, ranked (both stores with leaf and group), leaves and stairs, after ``geoms``."""
    return f"""size AS (SELECT count(*) AS n FROM boxes),
    ordered AS (SELECT zlen, row_number() OVER (ORDER BY zlen) AS r FROM boxes),
    cut AS (SELECT zlen AS threshold FROM ordered, size WHERE r = CAST(ceil(round({q} * n, 9)) AS BIGINT)),
    stored AS (SELECT b.*, CASE WHEN zlen > threshold THEN 1 ELSE 0 END AS store FROM boxes b, cut),
    ranked AS (SELECT *, rank0 // {cap} AS leaf_id FROM (SELECT *, row_number() OVER (PARTITION BY store ORDER BY zmin, zmax, geom_id) - 1 AS rank0 FROM stored)),
    leaves AS (SELECT store, leaf_id, min(zmin) AS first_key, max(zmin) AS last_key, count(*) AS n, min(x0) AS x0, min(y0) AS y0, max(x1) AS x1, max(y1) AS y1 FROM ranked GROUP BY store, leaf_id),
    mains AS (SELECT count(*) AS n FROM boxes),
    grouped AS (SELECT rank0 // (SELECT {m} FROM mains) AS g, min(zmin) AS start_key, max(zmax) AS hi FROM ranked WHERE store = 0 GROUP BY 1),
    reach AS (SELECT *, coalesce(max(hi) OVER (ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS lo FROM grouped),
    stairs AS (SELECT row_number() OVER (ORDER BY g) - 1 AS piece_id, lo AS lo_excl, hi AS hi_incl, start_key FROM reach WHERE hi > lo)"""


def starting(rel: str) -> str:
    """CTE begun: windows with the key from which each store is scanned."""
    if rel == "contains":
        return "begun AS (SELECT w.*, store, zlo AS zstart FROM windows w, (VALUES (0), (1)) s(store))"
    return """begun AS (SELECT w.*, 0 AS store, least(zlo, coalesce(start_key, zlo)) AS zstart FROM windows w LEFT JOIN stairs ON zlo > lo_excl AND zlo <= hi_incl
        UNION ALL SELECT w.*, 1 AS store, 0 AS zstart FROM windows w)"""


def checked(rel: str, leaf_skip: bool = True) -> str:
    """CTE seen (qid, checked)."""
    skip = " AND l.x0 <= w.wx1 AND l.x1 >= w.wx0 AND l.y0 <= w.wy1 AND l.y1 >= w.wy0" if leaf_skip else ""
    return f"""seen{'' if leaf_skip else '_all'} AS (SELECT q.qid, count(c.geom_id) AS checked FROM windows q LEFT JOIN (
        SELECT w.qid, r.geom_id FROM begun w JOIN leaves l ON l.store = w.store AND l.first_key <= w.zhi AND l.last_key >= w.zstart{skip}
        JOIN ranked r ON r.store = l.store AND r.leaf_id = l.leaf_id AND r.zmin BETWEEN w.zstart AND w.zhi) c ON c.qid = q.qid GROUP BY q.qid)"""


#: CTE quads (geom_id, qx0, qy0, side): each record's quadrant as a square, after ``geoms``.
QUADS = """lv AS (SELECT geom_id, x0, y0, least(20, 30 - CASE WHEN xor(zmin, zmax) = 0 THEN 0 ELSE (length(ltrim(bin(xor(zmin, zmax)), '0')) + 1) // 2 END) AS level FROM boxes),
    sq AS (SELECT geom_id, x0, y0, CAST(1 AS BIGINT) << CAST(30 - level AS INTEGER) AS side, level FROM lv),
    quads AS (SELECT geom_id, x0 - x0 % side AS qx0, y0 - y0 % side AS qy0, side, level FROM sq)"""

#: CTEs border (geom_id, x, y) and curve (x, y, h): border cells of parks on a grid of 128 cells, and the curve through it.
HILBERT = """cb AS (SELECT geom_id, x0 // 5625000 AS a, y0 // 5625000 AS b, x1 // 5625000 AS c, y1 // 5625000 AS d FROM boxes),
    border AS (SELECT DISTINCT geom_id, x, y FROM (
        SELECT geom_id, unnest(range(a, c + 1)) AS x, b AS y FROM cb UNION ALL SELECT geom_id, unnest(range(a, c + 1)), d FROM cb
        UNION ALL SELECT geom_id, a, unnest(range(b, d + 1)) FROM cb UNION ALL SELECT geom_id, c, unnest(range(b, d + 1)) FROM cb)),
    cells AS (SELECT DISTINCT x AS ox, y AS oy FROM border),
    walk AS (SELECT ox, oy, ox AS x, oy AS y, CAST(0 AS BIGINT) AS h FROM cells),
    """ + ",\n    ".join(
    f"""w{k} AS (SELECT ox, oy, CASE WHEN ry = 0 THEN (CASE WHEN rx = 1 THEN 127 - y ELSE y END) ELSE x END AS x,
        CASE WHEN ry = 0 THEN (CASE WHEN rx = 1 THEN 127 - x ELSE x END) ELSE y END AS y, h + {s} * {s} * xor(3 * rx, ry) AS h
        FROM (SELECT *, CASE WHEN x & {s} > 0 THEN 1 ELSE 0 END AS rx, CASE WHEN y & {s} > 0 THEN 1 ELSE 0 END AS ry FROM {'walk' if k == 0 else f'w{k - 1}'}))"""
    for k, s in enumerate((64, 32, 16, 8, 4, 2, 1))
) + """,
    curve AS (SELECT ox AS x, oy AS y, h FROM w6)"""

#: CTE touching (qid, geom_id): shapes whose part in the strip to the left of some park's box lies on its right side alone.
TOUCHING = """strips AS (SELECT geom_id AS qid, x0 - 4000 AS wx0, x0 AS wx1, y0 AS wy0, y1 AS wy1 FROM boxes),
    pairs AS (SELECT w.*, b.geom_id FROM strips w JOIN boxes b ON b.x0 <= w.wx1 AND b.x1 >= w.wx0 AND b.y0 <= w.wy1 AND b.y1 >= w.wy0),
    meets AS (SELECT qid, geom_id, bool_or(""" + (
    "(least(ax, bx) <= wx1 AND greatest(ax, bx) >= wx0 AND least(ay, ey) <= wy1 AND greatest(ay, ey) >= wy0 AND "
    + "least(" + ", ".join(_side(x, y) for x in ("wx0", "wx1") for y in ("wy0", "wy1")) + ") <= 0 AND greatest(" + ", ".join(_side(x, y) for x in ("wx0", "wx1") for y in ("wy0", "wy1")) + ") >= 0)"
) + """) AS border, """ + "sum(CASE WHEN (ay > wy0) <> (ey > wy0) AND (" + _side("wx0", "wy0") + """ > 0) = (ey > ay) THEN 1 ELSE 0 END) % 2 = 1 AS corner,
        bool_or(least(ax, bx) < wx1 AND greatest(ax, bx) > wx0 AND least(ay, ey) < wy1 AND greatest(ay, ey) > wy0) AS enters
        FROM pairs JOIN segs USING (geom_id) GROUP BY qid, geom_id),
    touching AS (SELECT qid, geom_id FROM meets WHERE border AND NOT corner AND NOT enters)"""


def sizes() -> str:
    """CTE sizes (method, part, bytes) of the index over both bases and of the trees, after ``stores``."""
    up = lambda n, f: f"(SELECT coalesce(sum(CASE WHEN {f} ** (k - 1) < {n} THEN ({n} + CAST({f} ** k AS BIGINT) - 1) // CAST({f} ** k AS BIGINT) ELSE 0 END), 0) FROM range(1, 12) t(k))"
    return f"""counts AS (SELECT count(*) FILTER (store = 0) AS l, count(*) FILTER (store = 1) AS ol FROM leaves),
    total AS (SELECT count(*) AS n FROM boxes),
    above AS (SELECT l, ol, CAST({up('l', 128)} AS BIGINT) AS inner_nodes FROM counts),
    tile AS (SELECT n, CAST(ceil(sqrt((n + 15) // 16)) AS BIGINT) AS strips FROM total),
    strip AS (SELECT n, (n + strips - 1) // strips AS per FROM tile),
    packed AS (SELECT n, n // per * ((per + 15) // 16) + (n % per + 15) // 16 AS nodes FROM strip),
    {QUADS},
    sizes AS (
        SELECT 'linear' AS method, 'inner' AS part, inner_nodes * 16 + (l + greatest(0, inner_nodes - 1)) * 8 AS bytes FROM above
        UNION ALL SELECT 'linear', 'leaves', l * 72 FROM above
        UNION ALL SELECT 'btree', 'inner', 16 * (CASE WHEN l > 1 THEN l + inner_nodes - 1 ELSE 0 END) FROM above
        UNION ALL SELECT 'btree', 'leaves', l * 56 FROM above
        UNION ALL SELECT m, 'staircase', 16 * (SELECT count(*) FROM stairs) FROM (VALUES ('linear'), ('btree')) v(m)
        UNION ALL SELECT m, 'outlier_leaves', 72 * ol FROM above, (VALUES ('linear'), ('btree')) v(m)
        UNION ALL SELECT m, 'entries', 16 * n FROM total, (VALUES ('linear'), ('btree')) v(m)
        UNION ALL SELECT 'rtree', 'nodes', 40 * (n + nodes + {up('nodes', 16)}) FROM packed
        UNION ALL SELECT 'quadtree', 'nodes', 40 * ((SELECT count(*) FROM (SELECT DISTINCT level, qx0, qy0 FROM quads)) + n) FROM total)"""


def with_(*ctes: str, select: str) -> str:
    return "WITH " + ",\n    ".join(ctes) + "\n" + select
