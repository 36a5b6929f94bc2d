"""Building: sort once by code, cut into leaves, box the leaves, model the keys, and lay the staircase.

A store is a folder of segments, ``seg=<k>/leaf_band=<b>/*.parquet``. The build is segment 0: bands are runs of neighbouring
leaves, at most ``MAX_BANDS`` of them, and rows are sorted by key inside, so that folders and row groups can be skipped.
Every later insert is a segment of its own, in band ``LOOSE`` until a compaction.
"""

from __future__ import annotations

import copy
import random
from dataclasses import dataclass, field, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from zspan.augment import outliers, staircase
from zspan.base import linear
from zspan.base.btree import BTreeIndex
from zspan.base.linear import LearnedIndex
from zspan.base.protocol import BaseIndex, IndexNotOrderPreserving, require_ordered_directory
from zspan.base.spline import SplineRadix
from zspan.config import IndexConfig
from zspan.plans import new_path, settle, with_rank

#: Leaves up to which the driver keeps a directory; bands of a store; leaves of a band at least; the band of inserts.
RESIDENT_LEAVES, MAX_BANDS, BAND_LEAVES, LOOSE = 1 << 20, 4096, 64, -1
#: Rows of a band at least, so that small leaves don't make small files.
BAND_ROWS = 1 << 14
#: Leaves up to which a resident directory also serves as a local table.
LOCAL_LEAVES = 1 << 16
BOX = ("x0", "y0", "x1", "y1")
BASES: dict[str, type[BaseIndex]] = {"adaptive_linear": LearnedIndex, "btree": BTreeIndex, "spline_radix": SplineRadix}


@dataclass(frozen=True)
class Directory:
    """Leaves as arrays by position."""

    leaf_id: np.ndarray
    band: np.ndarray
    first: np.ndarray
    last: np.ndarray
    n: np.ndarray
    box: np.ndarray
    first_rank: np.ndarray  # -1 where a leaf holds inserts only


@dataclass
class Store:
    """One sorted run of records: segments of files, the leaf directory, and the base over it."""

    root: str
    segments: tuple[int, ...]
    schema: T.StructType
    leaves: DataFrame  # leaf_id, leaf_band, pos, first_key, last_key, n, first_rank, box
    base: BaseIndex
    directory: Directory | None
    key: str = "zmin"

    @cached_property
    def rows(self) -> DataFrame:
        read = self.leaves.sparkSession.read.schema(self.schema).option("basePath", self.root)
        return read.parquet(*[f"{self.root}/seg={k}" for k in self.segments])

    @cached_property
    def bands(self) -> DataFrame:
        """(leaf_band, pos_lo, pos_hi, box): at most ``MAX_BANDS`` rows."""
        return settle(self.leaves.groupBy("leaf_band").agg(F.min("pos").alias("pos_lo"), F.max("pos").alias("pos_hi"), *box_of()))

    def base_router(self) -> BaseIndex:
        """The base without its tables: what tasks need to route keys by."""
        own = copy.copy(self.base)
        for name in ("tables", "distinct", "segments"):
            own.__dict__.pop(name, None)
        own.leaves = None
        return own

    def append(self, rows: DataFrame, segment: int, loose: bool = True) -> None:
        """Writes rows (with leaf_id, and leaf_band unless loose) as a segment."""
        rows = rows.withColumn("leaf_band", F.lit(LOOSE)) if loose else rows
        cols = [f.name for f in self.schema if f.name != "seg"]
        rows = rows.withColumns({c: F.lit(None).cast(self.schema[c].dataType) for c in cols if c not in rows.columns}).select(*[F.col(c).cast(self.schema[c].dataType) for c in cols])
        rows.sortWithinPartitions("leaf_band", self.key).write.mode("overwrite").partitionBy("leaf_band").parquet(f"{self.root}/seg={segment}")


def box_of() -> list[F.Column]:
    return [F.min("x0").alias("x0"), F.min("y0").alias("y0"), F.max("x1").alias("x1"), F.max("y1").alias("y1")]


@dataclass
class ZIndex:
    """An index at one version; every change makes a new one, the old stays readable."""

    config: IndexConfig
    main_store: Store
    outlier_store: Store | None
    stairs: DataFrame | None
    threshold: int | None
    tombstones: DataFrame | None = None  # geom_id, zmin, seq: hides equal records of earlier segments
    version: int = 0
    skipped: int = 0
    applied: dict = field(default_factory=dict)  # of each stream the last batch that is in
    stats: dict = field(default_factory=dict)

    def evolve(self, **changes) -> ZIndex:
        return replace(self, version=self.version + 1, **changes)

    def next_segment(self) -> int:
        """A number for what the next version writes: above all earlier ones, and its own among branches of this version."""
        return (self.version + 1 << 32) + random.getrandbits(31)

    @property
    def main(self) -> DataFrame:
        return self.main_store.rows

    @property
    def outlier(self) -> DataFrame | None:
        return self.outlier_store.rows if self.outlier_store else None

    @property
    def leaves(self) -> DataFrame:
        return self.main_store.leaves

    @property
    def outlier_leaves(self) -> DataFrame | None:
        return self.outlier_store.leaves if self.outlier_store else None

    @property
    def base(self) -> BaseIndex:
        return self.main_store.base

    @cached_property
    def steps(self) -> tuple[np.ndarray, np.ndarray] | None:
        """The staircase as arrays (hi_incl, start_key), where it is within the driver's bound."""
        got = self.stairs.select("hi_incl", "start_key").limit(RESIDENT_LEAVES + 1).toPandas().sort_values("hi_incl")
        return None if len(got) > RESIDENT_LEAVES else (got["hi_incl"].to_numpy(np.int64), got["start_key"].to_numpy(np.int64))

    @cached_property
    def leaf_models(self) -> DataFrame:
        """(leaf_id, slope, intercept, max_err): each leaf's line from keys to slots, trained over what was built."""
        rows = self.main.where(F.col("rank").isNotNull()).join(self.leaves.select("leaf_id", "first_rank"), "leaf_id")
        return settle(linear.leaf_models(rows.select("leaf_id", (F.col("rank") - F.col("first_rank")).alias("slot"), F.col(self.main_store.key).alias("zmin")), self.leaves))


def sort_by_zmin(df: DataFrame, partitions: int | None = None, sort_key: str = "zmin") -> DataFrame:
    """The one full shuffle: ranges of (key, other end, id), sorted inside."""
    by = [sort_key, "zmax" if sort_key == "zmin" else "zmin", "geom_id"]
    out = df.repartitionByRange(partitions, *by) if partitions else df.repartitionByRange(*by)
    return out.sortWithinPartitions(*by)


def leaf_directory(rows: DataFrame, key: str = "zmin") -> DataFrame:
    """One row a leaf: its keys' range, count and box."""
    return rows.groupBy("leaf_id").agg(F.min("leaf_band").alias("leaf_band"), F.min(key).alias("first_key"), F.max(key).alias("last_key"), F.count("*").alias("n"), F.min("rank").alias("first_rank"), *box_of())


def resident(leaves: DataFrame, bound: int = RESIDENT_LEAVES) -> Directory | None:
    """The directory on the driver in key order, or None beyond the bound: then searches and inserts probe by joins."""
    got = leaves.select("leaf_id", "leaf_band", "first_key", "last_key", "n", "first_rank", *BOX).limit(bound + 1).toPandas()
    if len(got) > bound:
        return None
    got = got.sort_values(["first_key", "last_key", "leaf_id"])
    col = lambda c: got[c].to_numpy(np.int64)
    return Directory(col("leaf_id"), col("leaf_band"), col("first_key"), col("last_key"), col("n"), np.stack([col(c) for c in BOX]), got["first_rank"].fillna(-1).to_numpy(np.int64))


def as_table(spark, d: Directory) -> DataFrame:
    """A resident directory as a table, on files where it is large."""
    cols = {"leaf_id": d.leaf_id, "leaf_band": d.band.astype(np.int32), "pos": np.arange(len(d.n)), "first_key": d.first, "last_key": d.last, "n": d.n, "first_rank": d.first_rank, **dict(zip(BOX, d.box, strict=True))}
    out = spark.createDataFrame(pa.table({k: pa.array(v) for k, v in cols.items()}))
    return settle(out) if len(d.n) > LOCAL_LEAVES else out


def positioned(leaves: DataFrame) -> DataFrame:
    """A directory with positions in key order, by joins."""
    by = ["first_key", "last_key", "leaf_id"]
    return settle(with_rank(leaves.repartitionByRange(*by).sortWithinPartitions(*by)).withColumn("pos", F.col("rank")).drop("rank", "part", "at"))


def indexed(root: str, segments: tuple[int, ...], schema: T.StructType, leaves: DataFrame | Directory, cfg: IndexConfig, spark, base: BaseIndex | None = None) -> Store:
    """A store over a directory, still without positions if it is a table; the base is refitted unless it is given unchanged."""
    own = leaves if isinstance(leaves, Directory) else resident(leaves)
    table = as_table(spark, own) if own is not None else leaves if "pos" in leaves.columns else positioned(leaves)
    if base is None:
        if cfg.base not in BASES:
            raise IndexNotOrderPreserving(f"{cfg.base} does not keep leaves in key order: exact answers can't be given")
        if own is None:
            require_ordered_directory(table)
        elif (own.last[:-1] > own.first[1:]).any():
            raise IndexNotOrderPreserving("leaves are not in key order: exact answers can't be given")
        err = max(1, cfg.max_err // 8)  # in leaves, where leaf models count slots
        base = BASES[cfg.base].fit(table, own.first if own else None, fanout=cfg.fanout, max_err=err, radix_bits=cfg.radix_bits)
    return Store(root, segments, schema, table, base, own, cfg.sort_key)


def build_store(rows: DataFrame, cfg: IndexConfig, label: str) -> Store:
    """Sorts, cuts and writes rows as segment 0 of a new store."""
    spark, key = rows.sparkSession, cfg.sort_key
    cap = max(1, int(cfg.leaf_cap * cfg.fill))
    ordered = sort_by_zmin(rows, cfg.partitions, key)
    if cfg.leaf_policy == "banded":
        at = F.monotonically_increasing_id()
        part, place = F.shiftright(at, 33), at.bitwiseAND(F.lit((1 << 33) - 1))
        placed = ordered.withColumn("rank", at).withColumn("leaf_id", F.shiftleft(part, 33) + F.floor(place / cap)).withColumn("leaf_band", F.pmod(part, F.lit(MAX_BANDS)).cast("int"))
    else:
        ranked = with_rank(ordered)
        leaves_at_most = -(-ranked._zspan_rows // cap)
        if cfg.leaf_policy == "adaptive":
            starts = settle(linear.adaptive_starts(ranked, key, cap, cfg.max_err))
            numbered = with_rank(starts.repartitionByRange("part", "at").sortWithinPartitions("part", "at").withColumnsRenamed({"part": "_part", "at": "_at"}))
            leaves_at_most = numbered._zspan_rows
            # a row belongs to the last start at or before it: one equi join on (partition, block of places)
            blocks = numbered.select("_part", "_at", F.col("rank").alias("leaf_id")).withColumn("_end", F.lead("_at").over(_by_part()))
            ends = ranked.groupBy(F.col("part").alias("_part")).agg(F.max("at").alias("_most"))
            blocks = blocks.join(ends, "_part").withColumn("_end", F.coalesce("_end", F.col("_most") + 1)).withColumn("_block", F.explode(F.sequence(F.floor(F.col("_at") / cap), F.floor((F.col("_end") - 1) / cap))))
            same = (F.col("part") == F.col("_part")) & (F.floor(F.col("at") / cap) == F.col("_block")) & (F.col("at") >= F.col("_at")) & (F.col("at") < F.col("_end"))
            placed = ranked.join(blocks.drop("_most"), same).drop("_part", "_at", "_end", "_block")
        else:
            placed = ranked.withColumn("leaf_id", F.floor(F.col("rank") / cap))
        width = max(BAND_LEAVES, -(-BAND_ROWS // cap), -(-leaves_at_most // MAX_BANDS))
        placed = placed.drop("part", "at").withColumn("leaf_band", F.floor(F.col("leaf_id") / width).cast("int"))
    schema = T.StructType([*placed.drop("leaf_band").schema.fields, T.StructField("seg", T.LongType()), T.StructField("leaf_band", T.IntegerType())])
    store = Store(new_path(spark, label), (0,), schema, placed, None, None, key)
    store.append(placed, 0, loose=False)
    return indexed(store.root, (0,), schema, leaf_directory(store.rows, key), cfg, spark)


def _by_part():
    from pyspark.sql import Window as W

    return W.partitionBy("_part").orderBy("_at")


def build_index(geoms: DataFrame, cfg: IndexConfig = IndexConfig()) -> ZIndex:
    """An index of geometries with boxes and intervals (geom_id, kind, rings, x0..y1, zmin, zmax, zlen)."""
    if cfg.sort_key != "zmin" and cfg.augment:
        raise ValueError("the staircase lowers a start in zmin order: sort by zmax without augmentation, for contains only")
    if cfg.leaf_policy == "banded" and cfg.augment and cfg.grouping != "leaf":
        cfg = replace(cfg, grouping="leaf")  # there is no global rank to count groups by
    if cfg.base not in BASES:
        raise IndexNotOrderPreserving(f"{cfg.base} does not keep leaves in key order: exact answers can't be given")
    have = geoms.where("zmin is not null")
    threshold = outliers.length_threshold(have, cfg.outlier_q, cfg.exact_threshold) if cfg.augment else None
    usual, long = outliers.split_outliers(have, threshold) if cfg.augment else (have, None)
    main = build_store(usual, cfg, "main")
    if not cfg.augment:
        return ZIndex(cfg, main, None, None, None)
    outlier = build_store(long, replace(cfg, leaf_policy="fixed"), "outlier")
    by_leaf = main.rows.join(small_dir(main.leaves), "leaf_id") if cfg.grouping == "leaf" else main.rows
    return ZIndex(cfg, main, outlier, settle(staircase.build(by_leaf, cfg.m, cfg.grouping)), threshold)


def small_dir(leaves: DataFrame) -> DataFrame:
    return leaves.select("leaf_id", "pos")
