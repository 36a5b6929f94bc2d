"""Bounding boxes of geometries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def vertices(rings: Column) -> Column:
    return F.flatten(rings)


def with_mbr(df: DataFrame, geom: str = "rings") -> DataFrame:
    """Adds x0, y0, x1, y1; null for a null or empty geometry."""
    v = vertices(F.col(geom))
    xs, ys = F.transform(v, lambda p: p["x"]), F.transform(v, lambda p: p["y"])
    return df.withColumns({"x0": F.array_min(xs), "y0": F.array_min(ys), "x1": F.array_max(xs), "y1": F.array_max(ys)})
