"""What a one-dimensional index must offer to carry the intervals, and the test that it keeps order.

A base indexes the first keys of the leaves. Positions count leaves in key order from 0; the position of a key is that of
the last leaf whose first key is not above it, or 0. Small bases answer on the driver (``locate``), any base by joins
(``probe``); both follow the base's own way down and count its comparisons.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


class IndexNotOrderPreserving(ValueError):
    """Raised for a base whose leaves, read in order, are not sorted by key."""


class BaseIndex(Protocol):
    leaves: DataFrame

    @classmethod
    def fit(cls, leaves: DataFrame, **settings) -> BaseIndex:
        """Trains over a directory (pos, first_key, ...)."""

    def refit(self, leaves: DataFrame) -> BaseIndex:
        """The same kind over a directory whose first keys changed by splits, merges or inserts before the first key."""

    def locate(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions, comparisons) of keys, on the driver."""

    def probe(self, keys: DataFrame, key: str, out: str) -> DataFrame:
        """``keys`` with the position of column ``key`` in ``out``, by joins with the base's tables."""

    def size_bytes(self) -> dict[str, int]: ...


def order_violations(leaves: DataFrame, leaf: str = "leaf_id", slot: str = "slot", key: str = "zmin") -> DataFrame:
    """Records whose key is less than that of the record before them in leaf order; none if the base keeps order.

    Leaves are checked inside, and each leaf's first key against the greatest key of the leaves before.
    """
    inner = leaves.withColumn("before", F.lag(key).over(W.partitionBy(leaf).orderBy(slot))).where(F.col(key) < F.col("before")).select(leaf, slot, key, "before")
    ends = leaves.groupBy(leaf).agg(F.min(slot).alias(slot), F.min_by(key, slot).alias(key), F.max(key).alias("most"))
    edge = ends.withColumn("before", F.max("most").over(W.orderBy(leaf).rowsBetween(W.unboundedPreceding, -1))).where(F.col(key) < F.col("before")).select(leaf, slot, key, "before")
    return inner.unionByName(edge)


def require_order(leaves: DataFrame, **names) -> None:
    if order_violations(leaves, **names).limit(1).count():
        raise IndexNotOrderPreserving("leaves are not in key order: exact answers can't be given")


def require_ordered_directory(leaves: DataFrame) -> None:
    """The same by leaves alone: a leaf may not start before the one ahead of it ends."""
    ahead = W.partitionBy(F.floor(F.col("pos") / 65536)).orderBy("pos")  # seams of blocks are checked by the second test
    inside = leaves.withColumn("before", F.lag("last_key").over(ahead)).where("first_key < before")
    seams = leaves.where("pos % 65536 in (0, 65535)").select(F.floor((F.col("pos") + 1) / 65536).alias("seam"), F.when(F.col("pos") % 65536 == 0, F.col("first_key")).alias("f"), F.when(F.col("pos") % 65536 == 65535, F.col("last_key")).alias("l"))
    broken = seams.groupBy("seam").agg(F.min("f").alias("f"), F.max("l").alias("l")).where("f < l")
    if inside.select("pos").limit(1).unionByName(broken.select(F.col("seam").alias("pos")).limit(1)).count():
        raise IndexNotOrderPreserving("leaves are not in key order: exact answers can't be given")
