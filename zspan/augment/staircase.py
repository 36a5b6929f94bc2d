"""The step function that lowers a scan's start so that an Intersects query misses nothing.

Piece (lo_excl, hi_incl] holds start_key, the least zmin of the first group of neighbouring intervals that reaches as far.
"""

from __future__ import annotations

from bisect import bisect_left

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.plans import cover, small, with_rank

PIECE = "piece_id long, lo_excl long, hi_incl long, start_key long"
#: Groups whose running ends are found on the driver; beyond, groups are summarised by as many blocks first.
_BLOCKS = 65_536


def table(spark, ends: np.ndarray, values: np.ndarray, floor: int = -1, first_id: int = 0) -> DataFrame:
    """Pieces of a staircase whose ends rise, as a table."""
    lo = np.r_[floor, ends[:-1]][: len(ends)]
    cols = {"piece_id": np.arange(len(ends)) + first_id, "lo_excl": lo, "hi_incl": ends, "start_key": values}
    return spark.createDataFrame(pa.table({k: pa.array(v, pa.int64()) for k, v in cols.items()}))


def lowered(ends: np.ndarray, values: np.ndarray, zmin: np.ndarray, zmax: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``apply_inserts`` on arrays (hi_incl, start_key): the new ones."""
    last = ends[-1] if len(ends) else -1
    low = np.full(len(ends), np.iinfo(np.int64).max)
    if len(ends):
        np.minimum.at(low, np.searchsorted(ends, np.minimum(zmax, last)), zmin)
    values = np.minimum(values, np.minimum.accumulate(low[::-1])[::-1])
    beyond = zmax > last
    order = np.lexsort((zmax[beyond], zmin[beyond]))
    a, b = zmin[beyond][order], zmax[beyond][order]
    rising = b > np.maximum.accumulate(np.r_[last, b])[:-1]
    return np.r_[ends, b[rising]], np.r_[values, a[rising]]


def _reach(groups: DataFrame, floor: int) -> DataFrame:
    """``groups`` (g, hi, ...) in order of g, with ``seen``: the farthest end before each, ``floor`` at least.

    Ends run over blocks of groups, a bounded number of them, then inside each block.
    """
    most = groups.agg(F.max("g")).first()[0] or 0
    shift = max(0, int(most).bit_length() - _BLOCKS.bit_length() + 1)
    blocked = groups.withColumn("_b", F.shiftright("g", shift))
    ends = blocked.groupBy("_b").agg(F.max("hi").alias("_hi"))
    ahead = ends.select("_b", F.max("_hi").over(W.orderBy("_b").rowsBetween(W.unboundedPreceding, -1)).alias("_ahead"))
    inside = F.max("hi").over(W.partitionBy("_b").orderBy("g").rowsBetween(W.unboundedPreceding, -1))
    return blocked.withColumn("_in", inside).join(small(ahead), "_b").withColumn("seen", F.greatest(F.coalesce("_in", F.lit(floor)), F.coalesce("_ahead", F.lit(floor)), F.lit(floor))).drop("_b", "_in", "_ahead")


def _pieces(groups: DataFrame, floor: int, first_id: int = 0) -> DataFrame:
    """Pieces of groups (g, start_key, hi) in order of g; those that reach no farther than earlier ones add none."""
    few = groups.select("g", "start_key", "hi").limit(_BLOCKS + 1).toPandas()
    if len(few) <= _BLOCKS:
        few = few.sort_values("g")
        hi = few["hi"].to_numpy(np.int64)
        seen = np.maximum.accumulate(np.r_[floor, hi])[:-1]
        at = hi > seen
        return table(groups.sparkSession, hi[at], few["start_key"].to_numpy(np.int64)[at], floor, first_id)
    kept = _reach(groups, floor).where("hi > seen")
    numbered = with_rank(kept.repartitionByRange("g").sortWithinPartitions("g"))
    return numbered.select((F.col("rank") + first_id).alias("piece_id"), F.col("seen").alias("lo_excl"), F.col("hi").alias("hi_incl"), "start_key")


def build(ranked: DataFrame, m: int | None, grouping: str = "count") -> DataFrame:
    """Pieces of intervals (zmin, zmax, rank in zmin order, pos of the leaf), ``m`` to a group; None: one group."""
    g = F.col("pos") if grouping == "leaf" else F.lit(0) if m is None else F.floor(F.col("rank") / m)
    return _pieces(ranked.groupBy(g.cast("long").alias("g")).agg(F.min("zmin").alias("start_key"), F.max("zmax").alias("hi")), -1)


def exact_lowest(df: DataFrame, windows: DataFrame) -> DataFrame:
    """(qid, lowest): the least zmin among intervals that end at zlo or later, by scan."""
    return small(windows.select("qid", "zlo")).join(df.select("zmin", "zmax"), F.col("zmax") >= F.col("zlo")).groupBy("qid").agg(F.min("zmin").alias("lowest"))


def augment(windows: DataFrame, stairs: DataFrame) -> DataFrame:
    """``windows`` with zstart, the lowered zlo; past the last piece it stays."""
    ends = stairs.agg(F.max("hi_incl")).first()[0] or 0
    hit = cover(windows, "zlo", stairs.select("lo_excl", "hi_incl", "start_key"), "lo_excl", "hi_incl", max(0, int(ends).bit_length() - 16))
    return hit.withColumn("zstart", F.least("zlo", F.coalesce("start_key", "zlo"))).drop("lo_excl", "hi_incl", "start_key")


def lookup(rows: list[tuple[int, int]], z: int) -> int:
    """The lowered start of one key; rows are (hi_incl, start_key) in order."""
    i = bisect_left([hi for hi, _ in rows], z)
    return min(z, rows[i][1]) if i < len(rows) else z


def apply_inserts(stairs: DataFrame, new: DataFrame) -> DataFrame:
    """Pieces after intervals (zmin, zmax) came in: values drop where those lie, and pieces follow for those beyond.

    A new interval lowers every piece that starts before its end. Pieces that end before its zmin hold less already, so
    the least zmin per piece of its end, run backwards over the pieces, is all that is needed.
    """
    n, last = stairs.agg(F.count("*"), F.max("hi_incl")).first()
    last = -1 if last is None else last
    ends = new.select("zmin", F.least("zmax", F.lit(last)).alias("_end"))
    low = cover(ends, "_end", stairs, "lo_excl", "hi_incl", max(0, int(last).bit_length() - 16), "inner").groupBy("piece_id").agg(F.min("zmin").alias("low"))
    later = W.orderBy("piece_id").rowsBetween(0, W.unboundedFollowing)  # one row a piece
    kept = stairs.join(low, "piece_id", "left").withColumn("low", F.min("low").over(later)).select("piece_id", "lo_excl", "hi_incl", F.least("start_key", F.coalesce("low", "start_key")).alias("start_key"))
    beyond = with_rank(new.where(F.col("zmax") > last).select("zmin", "zmax").repartitionByRange("zmin", "zmax").sortWithinPartitions("zmin", "zmax"))
    return kept.unionByName(_pieces(beyond.select(F.col("rank").alias("g"), F.col("zmin").alias("start_key"), F.col("zmax").alias("hi")), last, n))
