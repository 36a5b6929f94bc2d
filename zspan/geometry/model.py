"""Schemas of geometries."""

from __future__ import annotations

from pyspark.sql import types as T

POINT = T.StructType([T.StructField("x", T.LongType()), T.StructField("y", T.LongType())])
RINGS = T.ArrayType(T.ArrayType(POINT))
GEOMETRY = T.StructType([T.StructField("geom_id", T.LongType()), T.StructField("kind", T.StringType()), T.StructField("rings", RINGS)])
KINDS = ("POINT", "MULTIPOINT", "LINESTRING", "MULTILINESTRING", "POLYGON", "MULTIPOLYGON", "COLLECTION")
