"""Z-order intervals of geometries, and what they say of their relation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from zspan.curve.zorder import cell_of_units, z_address
from zspan.geometry.mbr import vertices
from zspan.plans import once


def with_zinterval(df: DataFrame, units_per_cell: int = 1) -> DataFrame:
    """Adds zmin, zmax, zlen from the corners of the box (x0, y0, x1, y1)."""
    code = lambda x, y: once((x, y, units_per_cell), lambda: z_address(cell_of_units(F.col(x), units_per_cell), cell_of_units(F.col(y), units_per_cell)))
    return df.withColumns({"zmin": code("x0", "y0"), "zmax": code("x1", "y1")}).withColumn("zlen", F.col("zmax") - F.col("zmin"))


def vertex_interval(df: DataFrame, geom: str = "rings") -> DataFrame:
    """The wrong interval, from the codes of the vertices: it misses cells of the box. Kept as a counter-example."""
    codes = F.transform(vertices(F.col(geom)), lambda p: z_address(p["x"], p["y"]))
    return df.withColumns({"vmin": F.array_min(codes), "vmax": F.array_max(codes)})


def z_contains(qlo: Column, qhi: Column, glo: Column, ghi: Column) -> Column:
    return glo.between(qlo, qhi) & ghi.between(qlo, qhi)


def z_overlaps(qlo: Column, qhi: Column, glo: Column, ghi: Column) -> Column:
    return (qlo <= ghi) & (glo <= qhi)


def dominates(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """Whether b is at least a in both coordinates; then b's code is at least a's."""
    return (ax <= bx) & (ay <= by)
