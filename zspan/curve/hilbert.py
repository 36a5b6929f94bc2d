"""Hilbert codes, to show why intervals over them need every cell of a box's border."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hilbert_address(x: Column, y: Column, order: int) -> Column:
    """Code of cell (x, y) on a grid of 2^order by 2^order cells."""
    start = F.struct(x.cast("long").alias("x"), y.cast("long").alias("y"), F.lit(0).cast("long").alias("d"))
    side = (1 << order) - 1

    def step(acc: Column, s: Column) -> Column:
        rx = F.when(acc["x"].bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        ry = F.when(acc["y"].bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        d = acc["d"] + s * s * (rx * 3).bitwiseXOR(ry)
        flip = (ry == 0) & (rx == 1)
        px, py = F.when(flip, F.lit(side) - acc["x"]).otherwise(acc["x"]), F.when(flip, F.lit(side) - acc["y"]).otherwise(acc["y"])
        return F.struct(F.when(ry == 0, py).otherwise(px).cast("long").alias("x"), F.when(ry == 0, px).otherwise(py).cast("long").alias("y"), d.cast("long").alias("d"))

    return F.aggregate(F.array([F.lit(1 << k).cast("long") for k in reversed(range(order))]), start, step)["d"]


def boundary_interval(boxes: DataFrame, order: int) -> DataFrame:
    """(geom_id, hmin, hmax, cells): the interval of each box from all cells on its border, on a coarse grid.

    Boxes are in cells of that grid: x0, y0, x1, y1.
    """
    across = F.transform(F.sequence("x0", "x1"), lambda x: F.array(F.struct(x.alias("x"), F.col("y0").alias("y")), F.struct(x.alias("x"), F.col("y1").alias("y"))))
    along = F.transform(F.sequence("y0", "y1"), lambda y: F.array(F.struct(F.col("x0").alias("x"), y.alias("y")), F.struct(F.col("x1").alias("x"), y.alias("y"))))
    cells = boxes.select("geom_id", F.explode(F.array_distinct(F.flatten(F.concat(across, along)))).alias("c"))
    return cells.groupBy("geom_id").agg(F.min(h := hilbert_address(F.col("c.x"), F.col("c.y"), order)).alias("hmin"), F.max(h).alias("hmax"), F.count("*").alias("cells"))
