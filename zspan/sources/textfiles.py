"""Geometries from text files: tables of points, tables with well-known text, and GeoJSON with one feature a line.

Schemas are given, so that no file is read twice to guess one; files split among tasks as any text does.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.curve.zorder import CELL, cell_x, cell_y
from zspan.geometry.text import from_geojson, from_wkt


def csv_points(spark: SparkSession, path: str, lon: str = "lon", lat: str = "lat", key: str = "geom_id", cell: float | None = CELL, columns: str | None = None) -> DataFrame:
    """geom_id, kind and rings of a table of points in degrees, or in whole units where ``cell`` is None.

    ``columns`` is the files' whole schema in order, by default the key and the two coordinates. Points without both go.
    """
    rows = spark.read.csv(path, schema=columns or f"{key} long, {lon} {'double' if cell else 'long'}, {lat} {'double' if cell else 'long'}", header=True)
    x, y = (cell_x(F.col(lon), cell), cell_y(F.col(lat), cell)) if cell else (F.col(lon).cast("long"), F.col(lat).cast("long"))
    rows = rows.where(F.col(lon).isNotNull() & F.col(lat).isNotNull())
    return rows.select(F.col(key).alias("geom_id"), F.lit("POINT").alias("kind"), F.array(F.array(F.struct(x.alias("x"), y.alias("y")))).alias("rings"))


def csv_wkt(spark: SparkSession, path: str, text: str = "wkt", key: str = "geom_id", columns: str | None = None) -> DataFrame:
    """geom_id, kind and rings of a table with well-known text in whole units."""
    rows = spark.read.csv(path, schema=columns or f"{key} long, {text} string", header=True, escape='"')
    return from_wkt(rows.withColumnRenamed(key, "geom_id"), text).select("geom_id", "kind", "rings")


def geojson_lines(spark: SparkSession, path: str, cell: float | None = CELL, key: str = "$.id") -> DataFrame:
    """geom_id (from the JSON path ``key``), kind and rings of newline-delimited features; lines without a geometry go."""
    rows = spark.read.text(path).select(F.get_json_object("value", key).cast("long").alias("geom_id"), "value")
    return from_geojson(rows, "value", cell).where("kind is not null").select("geom_id", "kind", "rings")
