"""Well-known text and GeoJSON, with built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from zspan.curve.zorder import cell_x, cell_y

# Type names of GeoJSON, by the depth at which their coordinates are nested.
_DEPTH = {1: ("Point",), 2: ("MultiPoint", "LineString"), 3: ("MultiLineString", "Polygon"), 4: ("MultiPolygon",)}


def to_wkt(kind: Column, rings: Column) -> Column:
    """Text of points, lines and polygons."""
    ring = lambda r: F.concat(F.lit("("), F.array_join(F.transform(r, lambda p: F.concat_ws(" ", p["x"].cast("string"), p["y"].cast("string"))), ", "), F.lit(")"))
    body = F.array_join(F.transform(rings, ring), ", ")
    return F.concat(kind, F.lit(" "), F.when(kind.isin("POLYGON", "MULTILINESTRING"), F.concat(F.lit("("), body, F.lit(")"))).otherwise(body))


def from_wkt(df: DataFrame, col: str) -> DataFrame:
    """Adds kind and rings; numbers are whole units, signs allowed."""
    inner = F.expr(f"regexp_extract_all({col}, '[(]([^()]+)[)]', 1)")
    point = lambda p: F.struct(F.split(F.trim(p), " +")[0].cast("long").alias("x"), F.split(F.trim(p), " +")[1].cast("long").alias("y"))
    rings = F.transform(inner, lambda r: F.transform(F.split(r, ","), point))
    return df.withColumns({"kind": F.upper(F.regexp_extract(col, r"^\s*(\w+)", 1)), "rings": rings})


def to_geojson(kind: Column, rings: Column) -> Column:
    """A geometry object in whole units; a polygon of several parts is written as rings of one."""
    body = F.to_json(F.transform(rings, lambda r: F.transform(r, lambda p: F.array(p["x"], p["y"]))))
    names = {n.upper(): (n, depth) for depth, some in _DEPTH.items() if depth < 4 for n in some} | {"MULTIPOLYGON": ("Polygon", 3)}
    out = F.lit(None).cast("string")
    for k, (n, depth) in names.items():
        cut = 3 - depth  # brackets around the one ring, or the one point
        out = F.when(kind == k, F.concat(F.lit(f'{{"type":"{n}","coordinates":'), body if not cut else body.substr(F.lit(1 + cut), F.length(body) - 2 * cut), F.lit("}"))).otherwise(out)
    return out


def from_geojson(df: DataFrame, col: str, cell: float | None = None) -> DataFrame:
    """Adds kind and rings of a geometry object, or of a feature's geometry.

    Numbers are whole units or, with ``cell``, degrees to be cut into cells of that size. The parts of a polygon of several
    parts become rings of one list. Null, malformed or empty geometries and other types give nulls.
    """
    geometry = F.coalesce(F.get_json_object(col, "$.geometry"), F.col(col))
    kind, inner = F.get_json_object(geometry, "$.type"), F.get_json_object(geometry, "$.coordinates")
    deep = F.when(kind.isin(*_DEPTH[1]), F.concat(F.lit("[[["), F.substr(inner, F.lit(2)), F.lit("]]")))
    deep = deep.when(kind.isin(*_DEPTH[2]), F.concat(F.lit("["), inner, F.lit("]"))).when(kind.isin(*_DEPTH[3]), inner)
    flat = F.when(kind.isin(*_DEPTH[4]), F.flatten(F.from_json(inner, "array<array<array<array<double>>>>"))).otherwise(F.from_json(deep, "array<array<array<double>>>"))
    x, y = ((lambda v: cell_x(v, cell)), (lambda v: cell_y(v, cell))) if cell else ((lambda v: v.cast("long")),) * 2
    point = lambda p: F.struct(x(F.get(p, F.lit(0))).alias("x"), y(F.get(p, F.lit(1))).alias("y"))
    df = df.withColumns({"kind": F.upper(kind), "rings": F.transform(flat, lambda r: F.transform(r, point))})
    lost = F.exists(F.flatten("rings"), lambda p: p["x"].isNull() | p["y"].isNull())
    known = (F.size(F.flatten("rings")) > 0) & ~lost
    return df.withColumns({"kind": F.when(known, F.col("kind")), "rings": F.when(known, F.col("rings"))})
