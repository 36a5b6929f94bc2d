"""A B-tree over the leaves' first keys: level tables of separators, searched by comparison."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zspan.base.search import bisect
from zspan.plans import written


def level_tables(leaves: DataFrame, fanout: int = 128) -> DataFrame:
    """(level, node, first_key): level 0 has the leaves, each level above a node for ``fanout`` below, up to one root."""
    level = leaves.select(F.lit(0).cast("long").alias("level"), F.col("pos").alias("node"), "first_key")
    out, n, depth = level, leaves.count(), 0
    while n > 1:
        depth += 1
        level = level.groupBy(F.floor(F.col("node") / fanout).cast("long").alias("node")).agg(F.min("first_key").alias("first_key")).select(F.lit(depth).cast("long").alias("level"), "node", "first_key")
        out, n = out.unionByName(level), -(-n // fanout)
    return out


def node_tables(leaves: DataFrame, fanout: int) -> list[DataFrame]:
    """For each level above the leaves, bottom up: (node, keys), the first keys of a node's children in order."""
    child, n, out = leaves.select(F.col("pos").alias("child"), "first_key"), leaves.count(), []
    while n > 1:
        run = F.sort_array(F.collect_list(F.struct("child", "first_key")))["first_key"]
        level = written(child.groupBy(F.floor(F.col("child") / fanout).cast("long").alias("node")).agg(run.alias("keys")), "nodes")
        out.append(level)
        child, n = level.select(F.col("node").alias("child"), F.col("keys")[0].alias("first_key")), -(-n // fanout)
    return out


@dataclass
class BTreeIndex:
    leaves: DataFrame
    fanout: int = 128
    keys: np.ndarray | None = field(default=None, repr=False)  # first keys by position, where the driver may hold them
    n: int = 0

    @classmethod
    def fit(cls, leaves: DataFrame, keys: np.ndarray | None = None, fanout: int = 128, **_) -> BTreeIndex:
        return cls(leaves, fanout, keys, len(keys) if keys is not None else leaves.count())

    def refit(self, leaves: DataFrame, keys: np.ndarray | None = None) -> BTreeIndex:
        return type(self).fit(leaves, keys, fanout=self.fanout)

    @cached_property
    def levels(self) -> list[np.ndarray]:
        """First keys by level, leaves first."""
        out = [self.keys]
        while len(out[-1]) > 1:
            out.append(out[-1][:: self.fanout])
        return out

    def locate(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        node, steps = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        for table in reversed(self.levels[:-1]):
            lo = node * self.fanout
            node, took = bisect(table, keys, lo, np.minimum(lo + self.fanout, len(table)))
            steps += took
        return node, steps

    @cached_property
    def tables(self) -> list[DataFrame]:
        return node_tables(self.leaves, self.fanout)

    def probe(self, keys: DataFrame, key: str, out: str) -> DataFrame:
        """One equi join a level; in a node, separators not above the key are counted."""
        at = keys.withColumn(out, F.lit(0).cast("long"))
        for level in reversed(self.tables):
            below = F.size(F.filter("keys", lambda k: k <= F.col(key)))
            at = at.join(level, F.col(out) == F.col("node")).withColumn(out, F.col("node") * self.fanout + F.greatest(below - 1, F.lit(0))).drop("node", "keys")
        return at

    def depth(self) -> int:
        return max(0, math.ceil(round(math.log(max(1, self.n), self.fanout), 9)))

    def size_bytes(self) -> dict[str, int]:
        """Inner nodes are separators with child pointers; leaves hold box, key range and count."""
        inner, level = 0, max(1, self.n)
        while level > 1:
            inner += level * 16
            level = -(-level // self.fanout)
        return {"inner": inner, "leaves": max(1, self.n) * (32 + 16 + 8)}
