"""Exact relations of a query window and a geometry, on integer coordinates.

Rectangular windows are tested with array functions inside the engine; any other window goes through an Arrow function.
Products of two coordinate differences stay below 2^61, so nothing is rounded.
"""

from __future__ import annotations

from fractions import Fraction

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_ROUND_KINDS = ("POLYGON", "MULTIPOLYGON")


def segments(ring: Column) -> Column:
    """A ring's edges as structs ax, ay, bx, by; a single vertex is an edge to itself."""
    n = F.size(ring)
    return F.transform(F.sequence(F.lit(1), F.greatest(n - 1, F.lit(1))), lambda i: F.struct(F.element_at(ring, i)["x"].alias("ax"), F.element_at(ring, i)["y"].alias("ay"), F.element_at(ring, F.least(i + 1, n))["x"].alias("bx"), F.element_at(ring, F.least(i + 1, n))["y"].alias("by")))


def all_segments(rings: Column) -> Column:
    return F.flatten(F.transform(F.filter(rings, lambda r: F.size(r) > 0), segments))


def _side(s: Column, x: Column, y: Column) -> Column:
    return (s["bx"] - s["ax"]) * (y - s["ay"]) - (s["by"] - s["ay"]) * (x - s["ax"])


def segment_meets(s: Column, wx0: Column, wx1: Column, wy0: Column, wy1: Column) -> Column:
    """Whether a segment shares a point with the closed rectangle."""
    overlap = (F.least(s["ax"], s["bx"]) <= wx1) & (F.greatest(s["ax"], s["bx"]) >= wx0) & (F.least(s["ay"], s["by"]) <= wy1) & (F.greatest(s["ay"], s["by"]) >= wy0)
    sides = [_side(s, x, y) for x in (wx0, wx1) for y in (wy0, wy1)]
    low, high = F.least(*sides), F.greatest(*sides)
    return overlap & (low <= 0) & (high >= 0)


def inside(rings: Column, x: Column, y: Column) -> Column:
    """Odd crossing parity of the half-line to the right of a point, over shells and holes together."""
    crossed = F.filter(all_segments(rings), lambda s: ((s["ay"] > y) != (s["by"] > y)) & ((_side(s, x, y) > 0) == (s["by"] > s["ay"])))
    return F.size(crossed) % 2 == 1


def intersects_rect(rings: Column, kind: Column, wx0: Column, wx1: Column, wy0: Column, wy1: Column, box: tuple[Column, Column, Column, Column] | None = None) -> Column:
    """A shape with its ``box`` (x0, x1, y0, y1) in the window shares all its points; others are tested edge by edge."""
    if box is not None:
        x0, x1, y0, y1 = box
        held = (x0 >= wx0) & (x1 <= wx1) & (y0 >= wy0) & (y1 <= wy1)
        return held | intersects_rect(rings, kind, wx0, wx1, wy0, wy1)
    meets = F.exists(all_segments(rings), lambda s: segment_meets(s, wx0, wx1, wy0, wy1))
    return meets | (kind.isin(*_ROUND_KINDS) & inside(rings, wx0, wy0))


def contains_rect(rings: Column, kind: Column, x0: Column, x1: Column, y0: Column, y1: Column, wx0: Column, wx1: Column, wy0: Column, wy1: Column) -> Column:
    """The box lies in the window and the geometry not wholly on the window's border; a flat window contains nothing."""
    on_border = F.forall(all_segments(rings), lambda s: ((s["ax"] == s["bx"]) & s["ax"].isin(wx0, wx1)) | ((s["ay"] == s["by"]) & s["ay"].isin(wy0, wy1)))
    return (wx0 < wx1) & (wy0 < wy1) & (x0 >= wx0) & (x1 <= wx1) & (y0 >= wy0) & (y1 <= wy1) & (kind.isin(*_ROUND_KINDS) | ((x0 > wx0) & (x1 < wx1) & (y0 > wy0) & (y1 < wy1)) | ~on_border)


# --- any window -----------------------------------------------------------------------------------------------------


def _edges(rings) -> list[tuple[int, int, int, int]]:
    out = []
    for r in rings:
        p = [(int(v["x"]), int(v["y"])) for v in r]
        out += [(*a, *b) for a, b in zip(p, p[1:], strict=False)] or [(*p[0], *p[0])] if p else []
    return out


def _cross(ax, ay, bx, by, px, py):
    return (bx - ax) * (py - ay) - (by - ay) * (px - ax)


def _on(e, px, py) -> bool:
    ax, ay, bx, by = e
    return _cross(ax, ay, bx, by, px, py) == 0 and min(ax, bx) <= px <= max(ax, bx) and min(ay, by) <= py <= max(ay, by)


def _touch(a, b) -> bool:
    sign = lambda v: (v > 0) - (v < 0)
    d = [sign(_cross(*a, *b[:2])), sign(_cross(*a, *b[2:])), sign(_cross(*b, *a[:2])), sign(_cross(*b, *a[2:]))]
    if d[0] * d[1] < 0 and d[2] * d[3] < 0:
        return True
    return _on(a, *b[:2]) or _on(a, *b[2:]) or _on(b, *a[:2]) or _on(b, *a[2:])


def _where(edges, px, py) -> int:
    """1 inside the area bounded by the edges, 0 on them, -1 outside."""
    odd = False
    for e in edges:
        if _on(e, px, py):
            return 0
        ax, ay, bx, by = e
        if (ay > py) != (by > py) and (_cross(ax, ay, bx, by, px, py) > 0) == (by > ay):
            odd = not odd
    return 1 if odd else -1


def _cuts(e, others) -> list[Fraction]:
    """Places along an edge, from 0 to 1, where other edges meet it."""
    ax, ay, bx, by = e
    dx, dy, at = bx - ax, by - ay, {Fraction(0), Fraction(1)}
    for ox, oy, px, py in others:
        ex, ey = px - ox, py - oy
        det = dx * ey - dy * ex
        if det:
            t, u = Fraction((ox - ax) * ey - (oy - ay) * ex, det), Fraction((ox - ax) * dy - (oy - ay) * dx, det)
            if 0 <= t <= 1 and 0 <= u <= 1:
                at.add(t)
        else:
            for x, y in ((ox, oy), (px, py)):
                if _on(e, x, y) and (dx or dy):
                    at.add(Fraction(x - ax, dx) if dx else Fraction(y - ay, dy))
    return sorted(at)


def _pieces(e, others):
    """Midpoints of the parts into which other edges cut an edge."""
    ax, ay, bx, by = e
    if (ax, ay) == (bx, by):
        yield ax, ay
        return
    cuts = _cuts(e, others)
    for s, t in zip(cuts, cuts[1:], strict=False):
        m = (s + t) / 2
        yield ax + (bx - ax) * m, ay + (by - ay) * m


def relation(rel: str, qkind: str, qrings, kind: str, rings) -> bool:
    """Whether window Q and geometry G stand in ``rel``: contains, intersects, disjoint or touches."""
    q, g = _edges(qrings), _edges(rings)
    if not q or not g:
        return rel == "disjoint"
    q_area, g_area = qkind in _ROUND_KINDS, kind in _ROUND_KINDS
    meet = any(_touch(a, b) for a in q for b in g) or (q_area and _where(q, *g[0][:2]) > 0) or (g_area and _where(g, *q[0][:2]) > 0)
    if rel == "intersects":
        return meet
    if rel == "disjoint":
        return not meet
    if rel == "contains":
        if not meet:
            return False
        if not q_area:  # a line or point holds what lies on it; its interior is all but the two ends
            if g_area or not all(any(_on(a, x, y) for a in q) for e in g for x, y in (*_pieces(e, q), e[:2], e[2:])):
                return False
            ends = {q[0][:2], q[-1][2:]} if qkind == "LINESTRING" and q[0][:2] != q[-1][2:] else set()
            return any((x, y) not in ends for e in g for x, y in _pieces(e, q))
        spots = [_where(q, x, y) for e in g for x, y in _pieces(e, q)]
        if min(spots) < 0 or any(_where(q, x, y) < 0 for e in g for x, y in (e[:2], e[2:])):
            return False
        if g_area:  # nothing of Q's outside, such as a hole, lies within G
            return not any(_where(g, x, y) > 0 for e in q for x, y in _pieces(e, g))
        return max(spots) > 0
    if rel == "touches":
        if not meet:
            return False
        if q_area and g_area:
            crossed = any(_where(q, x, y) > 0 for e in g for x, y in _pieces(e, q)) or any(_where(g, x, y) > 0 for e in q for x, y in _pieces(e, g))
            same = all(_where(q, x, y) == 0 for e in g for x, y in _pieces(e, q))
            return not crossed and not same
        if q_area or g_area:
            area, line = (q, g) if q_area else (g, q)
            return not any(_where(area, x, y) > 0 for e in line for x, y in _pieces(e, area))
        ends = lambda edges, k: {edges[0][:2], edges[-1][2:]} if k == "LINESTRING" and edges[0][:2] != edges[-1][2:] else set()
        inner_q = {(x, y) for e in q for x, y in _pieces(e, g)}
        inner_g = {(x, y) for e in g for x, y in _pieces(e, q)}
        shared = {p for p in inner_q if any(_on(e, *p) for e in g)} | {p for p in inner_g if any(_on(e, *p) for e in q)}
        points = {(e[0] + (e[2] - e[0]) * t, e[1] + (e[3] - e[1]) * t) for e in q for t in _cuts(e, g)}
        shared |= {p for p in points if any(_on(e, *p) for e in g)}
        return not any(p not in ends(q, qkind) and p not in ends(g, kind) for p in shared)
    raise ValueError(rel)


def _general(rel: pa.Array, qkind: pa.Array, qrings: pa.Array, kind: pa.Array, rings: pa.Array) -> pa.Array:
    rows = zip(*(c.to_pylist() for c in (rel, qkind, qrings, kind, rings)), strict=True)
    return pa.array([None if b is None or d is None else relation(r, a, b, c, d) for r, a, b, c, d in rows], pa.bool_())


#: (relation, kind and rings of the window, kind and rings of the geometry) -> boolean; null where a shape is null.
general = F.arrow_udf(_general, T.BooleanType())


def refine_general(pairs: DataFrame, rel: str) -> DataFrame:
    """The rows of ``pairs`` (qkind, qrings, kind, rings) whose window and geometry stand in ``rel``."""
    return pairs.where(general(F.lit(rel), "qkind", "qrings", "kind", "rings"))
