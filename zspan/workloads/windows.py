"""Query windows as boxes of nearest neighbours, and plans of mixed transactions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.index.build import Store, ZIndex
from zspan.plans import settle, small, with_rank

#: Share of the set that a window's neighbours make, as a fraction of whole numbers.
SELECTIVITIES = {"1pct": (1, 100), "01pct": (1, 1000), "001pct": (1, 10000)}


def _square(a: Column, b: Column) -> Column:
    return a * a + b * b


def _gap(a0: str, a1: str, b0: str, b1: str) -> Column:
    return F.greatest(F.lit(0).cast("long"), F.col(a0) - F.col(b1), F.col(b0) - F.col(a1))


def knn_windows(geoms: DataFrame, ix: ZIndex, sel: str, n: int = 100) -> DataFrame:
    """(qid, wx0, wx1, wy0, wy1): boxes around the nearest ``sel`` of all members to each of ``n`` evenly spaced ones.

    Distance is between boxes, squared, ties by id. The freshly built index of the same members bounds it: a leaf whose farthest
    member is surely among the nearest adds its box unread, one whose nearest member is surely beyond is skipped, and of the
    leaves between only members within the bound are ranked.
    """
    num, den = SELECTIVITIES[sel]
    total = geoms.count()
    k = max(1, -(-total * num // den))
    ranked = with_rank(geoms.select("geom_id", "x0", "y0", "x1", "y1").repartitionByRange("geom_id").sortWithinPartitions("geom_id"))
    wanted = geoms.sparkSession.createDataFrame([(i, i * total // n) for i in range(n)], "qid long, rank long")
    seeds = settle(ranked.join(F.broadcast(wanted), "rank").select("qid", *[F.col(c).alias("s" + c) for c in ("x0", "y0", "x1", "y1")]))
    stores: list[Store] = [s for s in (ix.main_store, ix.outlier_store) if s is not None]
    box = ["x0", "y0", "x1", "y1"]
    dirs = [s.leaves.select(F.lit(i).alias("store"), "leaf_id", "n", *box) for i, s in enumerate(stores)]
    leaves = dirs[0].unionByName(dirs[1]) if len(dirs) > 1 else dirs[0]
    nil = F.lit(0).cast("long")
    far_x = F.greatest(nil, F.col("x1") - F.col("sx1"), F.col("sx0") - F.col("x0"))
    far_y = F.greatest(nil, F.col("y1") - F.col("sy1"), F.col("sy0") - F.col("y0"))
    near = F.broadcast(seeds).join(leaves).withColumns({"least": _square(_gap("x0", "x1", "sx0", "sx1"), _gap("y0", "y1", "sy0", "sy1")), "most": _square(far_x, far_y)})
    by = W.partitionBy("qid")  # rows of a seed are leaves
    held = near.withColumns({"by_most": F.sum("n").over(by.orderBy("most")), "by_least": F.sum("n").over(by.orderBy("least"))})
    bounds = held.withColumns({"upper": F.min(F.when(F.col("by_most") >= k, F.col("most"))).over(by), "lower": F.min(F.when(F.col("by_least") >= k, F.col("least"))).over(by)})
    cut = settle(bounds.where("least <= upper").withColumn("whole", F.col("most") < F.col("lower")).select("qid", "store", "leaf_id", "n", *box, "whole", "upper"))
    sure = cut.where("whole").groupBy("qid").agg(F.sum("n").alias("sure"))
    open_ = cut.where("not whole").select("qid", "store", "leaf_id", "upper").join(F.broadcast(seeds), "qid").join(small(sure), "qid", "left")
    asked = None
    for i, s in enumerate(stores):
        own = s.rows.select("leaf_id", "geom_id", *box).join(small(open_.where(F.col("store") == i).drop("store")), "leaf_id")
        asked = own if asked is None else asked.unionByName(own)
    dist = _square(_gap("x0", "x1", "sx0", "sx1"), _gap("y0", "y1", "sy0", "sy1"))
    picked = asked.where(dist <= F.col("upper")).withColumn("r", F.row_number().over(by.orderBy(dist, "geom_id"))).where(F.col("r") <= k - F.coalesce("sure", nil))
    boxes = picked.select("qid", *box).unionByName(cut.where("whole").select("qid", *box))
    return boxes.groupBy("qid").agg(F.min("x0").alias("wx0"), F.max("x1").alias("wx1"), F.min("y0").alias("wy0"), F.max("y1").alias("wy1"))


def is_bulk() -> F.Column:
    """The half that is loaded at once; the rest is inserted or deleted."""
    return arrival() % 100 < 50


def arrival() -> F.Column:
    return (F.col("geom_id") * 1103515245 + 12345) % 2147483648


def transactions(read_share: float, inserts: int = 50) -> list[tuple[int, str]]:
    """(step, op): inserts spread evenly among queries, so that ``read_share`` of all steps are queries."""
    every = round(1 / (1 - read_share))
    return [(s, "insert" if s % every == every - 1 else "query") for s in range(inserts * every)]
