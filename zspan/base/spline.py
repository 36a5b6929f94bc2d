"""A spline over the leaves' first keys with a radix table over the keys' top bits."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.base.search import bisect, gallop
from zspan.plans import cover, with_rank, written


def corridor(keys: np.ndarray, ranks: np.ndarray, max_err: int) -> list[tuple[int, int]]:
    """Greedy knots (key, rank) over rising keys, so that lines between them miss no rank by more than ``max_err``."""
    if not len(keys):
        return []
    base, low, high = (int(keys[0]), int(ranks[0])), None, None
    out = [base]
    for i in range(1, len(keys)):
        k, r = int(keys[i]), int(ranks[i])
        dx = k - base[0]
        if low is not None and not (low[0] * dx <= (r - base[1]) * low[1] and (r - base[1]) * high[1] <= high[0] * dx):
            base = (int(keys[i - 1]), int(ranks[i - 1]))
            out.append(base)
            dx, low, high = k - base[0], None, None
        lo, hi = (r - max_err - base[1], dx), (r + max_err - base[1], dx)
        low = lo if low is None or lo[0] * low[1] > low[0] * lo[1] else low
        high = hi if high is None or hi[0] * high[1] < high[0] * hi[1] else high
    if len(keys) > 1:
        out.append((int(keys[-1]), int(ranks[-1])))
    return out


@dataclass
class SplineRadix:
    """A lookup takes the key's radix bucket, the knots around the key there, the line between them, and searches nearby."""

    leaves: DataFrame
    max_err: int = 8
    bits: int = 10
    keys: np.ndarray | None = field(default=None, repr=False)
    n: int = 0

    @classmethod
    def fit(cls, leaves: DataFrame, keys: np.ndarray | None = None, max_err: int = 8, radix_bits: int = 10, **_) -> SplineRadix:
        out = cls(leaves, max_err, radix_bits, keys, len(keys) if keys is not None else leaves.count())
        if keys is not None:
            out.knots  # noqa: B018
        return out

    def refit(self, leaves: DataFrame, keys: np.ndarray | None = None) -> SplineRadix:
        return type(self).fit(leaves, keys, max_err=self.max_err, radix_bits=self.bits)

    @cached_property
    def knots(self) -> tuple[np.ndarray, np.ndarray]:
        own, last = np.unique(self.keys[::-1], return_index=True)  # the last leaf of equal first keys
        got = corridor(own, len(self.keys) - 1 - last, self.max_err)
        return np.array([k for k, _ in got], np.int64), np.array([r for _, r in got], np.int64)

    @cached_property
    def radix(self) -> tuple[int, int, np.ndarray]:
        """(least key, shift, first knot of every bucket)."""
        keys = self.knots[0]
        least = int(keys[0]) if len(keys) else 0
        shift = max(0, (int(keys[-1]) - least).bit_length() - self.bits) if len(keys) else 0
        edges = least + (np.arange((1 << self.bits) + 1, dtype=np.int64) << shift)
        return least, shift, np.searchsorted(keys, edges)

    def locate(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not self.n:
            return np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        (knots, ranks), (least, shift, table) = self.knots, self.radix
        q = np.clip(keys, least, self.keys[-1])
        bucket = np.minimum((q - least) >> shift, (1 << self.bits) - 1)
        at, steps = bisect(knots, q, np.maximum(table[bucket] - 1, 0), np.maximum(table[bucket + 1], 1))
        after = np.minimum(at + 1, len(knots) - 1)
        width = np.maximum(knots[after] - knots[at], 1)
        guess = ranks[at] + (ranks[after] - ranks[at]) * ((q - knots[at]) / width)
        pos, took = gallop(self.keys, keys, np.zeros(len(q), np.int64), np.full(len(q), self.n), np.rint(guess).astype(np.int64))
        return pos, steps + took

    @cached_property
    def distinct(self) -> DataFrame:
        """(first_key, pos, rank): the distinct first keys with the last leaf that starts there, ranked."""
        last = self.leaves.groupBy("first_key").agg(F.max("pos").alias("pos"))
        return with_rank(last.repartitionByRange("first_key").sortWithinPartitions("first_key")).select("first_key", "pos", "rank")

    @cached_property
    def segments(self) -> DataFrame:
        """(lo, hi, k0, r0, k1, r1): lines between knots over ranks, trained by range partition and stitched; for keys in (lo, hi]."""
        err = self.max_err

        def run(batches):
            got = [(b.column("first_key").to_numpy(), b.column("rank").to_numpy()) for b in batches]
            knots = corridor(np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got]), err) if got else []
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in knots], pa.int64()), pa.array([r for _, r in knots], pa.int64())], names=["k0", "r0"])

        knots = self.distinct.repartitionByRange("first_key").sortWithinPartitions("first_key").select("first_key", "rank").mapInArrow(run, "k0 long, r0 long")
        order = W.orderBy("k0")  # one row a knot
        ends = knots.select("k0", "r0", F.coalesce(F.lead("k0").over(order), F.col("k0") + 1).alias("k1"), F.coalesce(F.lead("r0").over(order), F.col("r0")).alias("r1"))
        return written(ends.select((F.col("k0") - 1).alias("lo"), (F.col("k1") - 1).alias("hi"), "k0", "r0", "k1", "r1"), "segments")

    def probe(self, keys: DataFrame, key: str, out: str) -> DataFrame:
        """Radix join with the segments, a guess by the line, and a join with the few first keys around it."""
        least, most = self.segments.agg(F.min("k0"), F.max("hi")).first()
        if least is None:
            return keys.withColumn(out, F.lit(0).cast("long"))
        shift = max(0, (most - least).bit_length() - self.bits)
        named = keys.withColumn("_id", F.monotonically_increasing_id()).withColumn("_q", F.least(F.greatest(F.col(key), F.lit(least)), F.lit(most)) - least)
        pieces = self.segments.select("r0", "r1", *[(F.col(c) - least).alias("_" + c) for c in ("lo", "hi", "k0", "k1")])
        got = cover(named, "_q", pieces, "_lo", "_hi", shift, "inner")
        guess = F.round(F.col("r0") + (F.col("r1") - F.col("r0")) * ((F.col("_q") - F.col("_k0")) / (F.col("_k1") - F.col("_k0")))).cast("long")
        near = got.withColumn("_g", guess).withColumn("rank", F.explode(F.sequence(F.greatest(F.col("_g") - self.max_err - 2, F.lit(0)), F.col("_g") + self.max_err + 2)))
        best = near.join(self.distinct.withColumnsRenamed({"first_key": "_first", "pos": "_pos"}), "rank").where((F.col("_first") <= F.col(key)) | (F.col("rank") == 0))
        best = best.groupBy("_id").agg(F.max_by("_pos", "rank").alias("_pos"), F.max(F.when(F.col("_first") <= F.col(key), 1).otherwise(0)).alias("_in"), F.first(F.struct(*keys.columns)).alias("_row"))
        return best.select("_row.*", F.when(F.col("_in") == 1, F.col("_pos")).otherwise(F.lit(0)).cast("long").alias(out))

    def size_bytes(self) -> dict[str, int]:
        knots = len(self.knots[0]) if self.keys is not None else self.segments.count()
        return {"inner": 16 * knots + 4 * ((1 << self.bits) + 1), "leaves": max(1, self.n) * (32 + 16 + 8)}
