"""The learned base: linear models by region over the leaves' first keys, linear models of slots in leaves, adaptive leaves."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.base.search import gallop
from zspan.plans import written

MODEL, CHILD, BOX, KEYS, COUNT = 16, 8, 32, 16, 8


def leaf_models(rows: DataFrame, leaves: DataFrame) -> DataFrame:
    """(leaf_id, slope, intercept, max_err) of slot on key - first_key; the error is taken to a key's first slot.

    ``rows`` are (leaf_id, slot, zmin). Keys are rebased, since codes exceed what a double holds.
    """
    first = rows.groupBy("leaf_id", "zmin").agg(F.min("slot").alias("slot"), F.count("*").alias("same"))
    own = rows.join(leaves.select("leaf_id", "first_key", "n"), "leaf_id").withColumn("t", (F.col("zmin") - F.col("first_key")).cast("double"))
    fit = own.groupBy("leaf_id").agg(F.regr_slope("slot", "t").alias("s"), F.avg("slot").alias("ym"), F.avg("t").alias("tm"))
    fit = fit.select("leaf_id", F.coalesce("s", F.lit(0.0)).alias("slope"), (F.col("ym") - F.coalesce("s", F.lit(0.0)) * F.col("tm")).alias("intercept"))
    err = first.join(leaves.select("leaf_id", "first_key", "n"), "leaf_id").join(fit, "leaf_id").groupBy("leaf_id").agg(F.max(F.abs(F.col("slot") - predicted_slot(F.col("zmin")))).cast("long").alias("max_err"))
    return fit.join(err, "leaf_id")


def predicted_slot(key: F.Column) -> F.Column:
    """A leaf model's guess for a key, from columns slope, intercept, first_key and n."""
    return F.least(F.greatest(F.round(F.col("intercept") + F.col("slope") * (key - F.col("first_key"))), F.lit(0.0)), F.col("n") - 1.0).cast("long")


def adaptive_cuts(keys: np.ndarray, leaf_cap: int, max_err: int, fan: int = 4) -> list[int]:
    """Positions where leaves start: key ranges are split in ``fan`` until a range holds few keys that a line fits well."""

    def fits(own: np.ndarray) -> bool:
        if len(own) > leaf_cap:
            return False
        t, y = (own - own[0]).astype(float), np.arange(len(own))
        var = t.var()
        slope = ((t - t.mean()) * (y - y.mean())).mean() / var if var else 0.0
        return np.abs(y - (y.mean() + slope * (t - t.mean()))).max(initial=0) <= max_err

    out: list[int] = []
    todo = [(0, len(keys), int(keys[0]), int(keys[-1]) + 1)] if len(keys) else []
    while todo:
        a, b, lo, hi = todo.pop()
        own = keys[a:b]
        if not len(own):
            continue
        if own[0] == own[-1] or hi - lo < fan or fits(own):
            out.append(a)
            continue
        edges = [lo + (hi - lo) * k // fan for k in range(fan + 1)]
        at = [a, *(a + np.searchsorted(own, edges[1:-1])).tolist(), b]
        todo += zip(at, at[1:], edges, edges[1:], strict=False)
    return sorted(out)


def adaptive_starts(placed: DataFrame, key: str, leaf_cap: int, max_err: int) -> DataFrame:
    """(part, at): positions in range partitions where leaves start; ``placed`` has (part, at, key), in order by part."""

    def run(part: tuple[pa.Scalar, ...], own: pa.Table) -> pa.Table:
        cuts = adaptive_cuts(np.sort(own.column(key).to_numpy()), leaf_cap, max_err)
        return pa.table({"part": pa.array([part[0].as_py()] * len(cuts), pa.int64()), "at": pa.array(cuts, pa.int64())})

    return placed.select("part", key).groupBy("part").applyInArrow(run, "part long, at long")


def _fit_line(t: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    var = t.var()
    slope = float(((t - t.mean()) * (y - y.mean())).mean() / var) if var else 0.0
    return slope, float(y.mean() - slope * t.mean())


@dataclass
class LearnedIndex:
    """A tree of linear models: a node predicts its child by a line, and searches outwards from there."""

    leaves: DataFrame
    fanout: int = 128
    keys: np.ndarray | None = field(default=None, repr=False)  # first keys by position, where the driver may hold them
    n: int = 0

    @classmethod
    def fit(cls, leaves: DataFrame, keys: np.ndarray | None = None, fanout: int = 128, **_) -> LearnedIndex:
        out = cls(leaves, fanout, keys, len(keys) if keys is not None else leaves.count())
        if keys is not None:
            out.levels  # noqa: B018 - trained with the index, not by its first search
        return out

    def refit(self, leaves: DataFrame, keys: np.ndarray | None = None) -> LearnedIndex:
        return type(self).fit(leaves, keys, fanout=self.fanout)

    @cached_property
    def levels(self) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Bottom up: (children's first keys, and for each node first key, slope, intercept)."""
        out, keys = [], self.keys
        while len(keys) > 1:
            first = keys[:: self.fanout]
            lines = [_fit_line((own - own[0]).astype(float), np.arange(len(own))) for own in (keys[i : i + self.fanout] for i in range(0, len(keys), self.fanout))]
            out.append((keys, first, np.array([s for s, _ in lines]), np.array([c for _, c in lines])))
            keys = first
        return out

    def locate(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        node, steps = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        for table, first, slope, intercept in reversed(self.levels):
            lo = node * self.fanout
            guess = np.rint(intercept[node] + slope[node] * (keys - first[node]))
            hi = np.minimum(lo + self.fanout, len(table))
            node, took = gallop(table, keys, lo, hi, lo + np.clip(guess, 0, hi - lo - 1).astype(np.int64))
            steps += took
        return node, steps

    @cached_property
    def tables(self) -> list[DataFrame]:
        """For each level, bottom up: (node, keys, slope, intercept, max_err)."""
        from zspan.base.btree import node_tables

        out = []
        for level in node_tables(self.leaves, self.fanout):
            flat = level.select("node", F.posexplode("keys").alias("slot", "k"), F.col("keys")[0].alias("first")).withColumn("t", (F.col("k") - F.col("first")).cast("double"))
            fit = flat.groupBy("node").agg(F.coalesce(F.regr_slope("slot", "t"), F.lit(0.0)).alias("slope"), F.avg("slot").alias("ym"), F.avg("t").alias("tm"))
            fit = fit.select("node", "slope", (F.col("ym") - F.col("slope") * F.col("tm")).alias("intercept"))
            guess = F.round(F.col("intercept") + F.col("slope") * F.col("t"))
            err = flat.join(fit, "node").groupBy("node").agg(F.max(F.abs(guess - F.col("slot"))).cast("int").alias("max_err"))
            out.append(written(level.join(fit, "node").join(err, "node"), "models"))
        return out

    def probe(self, keys: DataFrame, key: str, out: str) -> DataFrame:
        """One equi join a level; in a node, only children within the model's error of its guess are compared.

        Between two fitted keys the guess lies between theirs, so one more child on either side suffices.
        """
        at = keys.withColumn(out, F.lit(0).cast("long"))
        for level in reversed(self.tables):
            n = F.size("keys")
            guess = F.round(F.col("intercept") + F.col("slope") * (F.col(key) - F.col("keys")[0]))
            near = F.least(F.greatest(guess, F.lit(0.0)), (n - 1).cast("double")).cast("int")
            lo = F.greatest(near - F.col("max_err") - 1, F.lit(0))
            below = F.size(F.filter(F.slice("keys", lo + 1, 2 * F.col("max_err") + 3), lambda k: k <= F.col(key)))
            at = at.join(level, F.col(out) == F.col("node")).withColumn(out, F.col("node") * self.fanout + F.greatest(lo + below - 1, F.lit(0))).drop("node", "keys", "slope", "intercept", "max_err")
        return at

    def depth(self) -> int:
        n, depth = max(1, self.n), 0
        while n > 1:
            n, depth = -(-n // self.fanout), depth + 1
        return depth

    def size_bytes(self) -> dict[str, int]:
        n, inner = max(1, self.n), 0
        level = n
        while level > 1:
            level = -(-level // self.fanout)
            inner += level
        return {"inner": inner * MODEL + (n + max(0, inner - 1)) * CHILD, "leaves": n * (BOX + KEYS + MODEL + COUNT)}


def two_stage(rows: DataFrame, fan: int = 16) -> DataFrame:
    """Leaves of a two-stage model whose root is a cubic that does not rise everywhere: it fails the order test.

    Returns (leaf_id, slot, zmin).
    """
    t = F.col("zmin") / F.lit(float(1 << 59))
    guess = F.pmod(F.floor((8 * t * t * t - 10 * t * t + 3.5 * t) * fan), F.lit(fan)).cast("long")
    return rows.select(guess.alias("leaf_id"), "zmin", "geom_id").withColumn("slot", F.row_number().over(W.partitionBy("leaf_id").orderBy("zmin", "geom_id")) - 1).select("leaf_id", "slot", "zmin")
