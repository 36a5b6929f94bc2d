"""Inserts, deletes, compaction and rebuilds; every change gives a new version of the index, the old one stays readable."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.augment import outliers, staircase
from zspan.index.build import BOX, Directory, Store, ZIndex, build_index, indexed, leaf_directory, small_dir
from zspan.index.query import alive
from zspan.plans import settle, small, with_rank

_ROW = ["geom_id", "kind", "rings", "x0", "y0", "x1", "y1", "zmin", "zmax", "zlen"]
#: Loose segments of a store after which its next insert compacts it.
LOOSE_SEGMENTS = 16
#: Rows of a batch whose keys and boxes the driver may hold.
BATCH_ROWS = 1 << 18


def route(store: Store, rows: DataFrame) -> DataFrame:
    """``rows`` with the leaf_id of the last leaf that starts at or before their key, or of the first leaf, by the base."""
    if not store.base.n:
        return rows.withColumn("leaf_id", F.lit(0).cast("long"))
    if store.directory is None:
        return store.base.probe(rows, store.key, "_pos").join(store.leaves.select(F.col("pos").alias("_pos"), "leaf_id"), "_pos").drop("_pos")
    shared = rows.sparkSession.sparkContext.broadcast((store.base_router(), store.directory.leaf_id))

    @F.pandas_udf("long")
    def leaf(k):
        import pandas as pd

        base, ids = shared.value
        return pd.Series(ids[base.locate(k.to_numpy(np.int64))[0]])

    return rows.withColumn("leaf_id", leaf(F.col(store.key)))


def merged(leaves: DataFrame, delta: DataFrame) -> DataFrame:
    """The directory after rows came in: ranges, counts and boxes only grow; positions stay."""
    box = [F.least(F.col(c), F.coalesce("d_" + c, c)).alias(c) for c in ("x0", "y0")] + [F.greatest(F.col(c), F.coalesce("d_" + c, c)).alias(c) for c in ("x1", "y1")]
    new = delta.select(*[F.col(c).alias("d_" + c) for c in delta.columns])
    keys = [F.least("first_key", F.coalesce("d_first_key", "first_key")).alias("first_key"), F.greatest("last_key", F.coalesce("d_last_key", "last_key")).alias("last_key")]
    return leaves.join(new, F.col("leaf_id") == F.col("d_leaf_id"), "left").select("leaf_id", "leaf_band", "pos", *keys, (F.col("n") + F.coalesce("d_n", F.lit(0))).alias("n"), "first_rank", *box)


def _place(store: Store, new: DataFrame, segment: int, ix: ZIndex) -> Store:
    """The store with ``new`` as a loose segment."""
    store.append(route(store, new), segment)
    grown = replace(store, segments=(*store.segments, segment))
    delta = leaf_directory(grown.rows.where(F.col("seg") == segment), store.key)
    spark = new.sparkSession
    if not store.base.n:
        return indexed(store.root, grown.segments, store.schema, delta, ix.config, spark)
    if store.directory is None:
        return indexed(store.root, grown.segments, store.schema, settle(merged(store.leaves, delta)), ix.config, spark, store.base)
    d, got = store.directory, delta.toPandas()  # within the directory's bound
    order = np.argsort(d.leaf_id)
    at = order[np.searchsorted(d.leaf_id, got["leaf_id"].to_numpy(np.int64), sorter=order)]
    first, last, n, box = d.first.copy(), d.last.copy(), d.n.copy(), d.box.copy()
    first[at], last[at], n[at] = np.minimum(first[at], got["first_key"]), np.maximum(last[at], got["last_key"]), n[at] + got["n"]
    for i, c in enumerate(BOX):
        box[i, at] = (np.minimum if i < 2 else np.maximum)(box[i, at], got[c])
    return indexed(store.root, grown.segments, store.schema, Directory(d.leaf_id, d.band, first, last, n, box, d.first_rank), ix.config, spark, store.base)


def _placed_here(store: Store, own: dict[str, np.ndarray], rows: DataFrame, segment: int, ix: ZIndex) -> Store:
    """``_place`` for a small batch, whose keys and boxes the driver holds: the directory grows without a second pass."""
    if not len(own["geom_id"]):
        return store
    d = store.directory
    pos, _ = store.base.locate(own[store.key])
    store.append(route(store, rows), segment)
    first, last, n, box = d.first.copy(), d.last.copy(), d.n.copy(), d.box.copy()
    np.minimum.at(first, pos, own[store.key])
    np.maximum.at(last, pos, own[store.key])
    np.add.at(n, pos, 1)
    for i, c in enumerate(BOX):
        (np.minimum if i < 2 else np.maximum).at(box[i], pos, own[c])
    grown = Directory(d.leaf_id, d.band, first, last, n, box, d.first_rank)
    return indexed(store.root, (*store.segments, segment), store.schema, grown, ix.config, rows.sparkSession, store.base)


def insert(ix: ZIndex, rows: DataFrame, upsert: bool = False) -> ZIndex:
    """Adds geometries (with boxes and intervals): routed to leaves, boxes grown, the staircase lowered where needed.

    ``upsert``: they take the place of live records of equal (geom_id, zmin).
    """
    rows = settle(rows.where("zmin is not null").select(*[c for c in _ROW if c in rows.columns]))
    usual, long = outliers.split_outliers(rows, ix.threshold) if ix.threshold is not None else (rows, None)
    segment = ix.next_segment()
    own = [s for s in (ix.main_store, ix.outlier_store) if s is not None]
    small_batch = None
    if all(s.directory is not None and s.base.n for s in own) and (ix.stairs is None or ix.steps is not None):
        got = rows.select("geom_id", *BOX, "zmin", "zmax", "zlen").limit(BATCH_ROWS + 1).toArrow()
        small_batch = {c: got.column(c).to_numpy() for c in got.column_names} if got.num_rows <= BATCH_ROWS else None
    changes: dict = {}
    if small_batch is not None:
        is_long = small_batch["zlen"] > ix.threshold if ix.threshold is not None else np.zeros(len(small_batch["zlen"]), bool)
        near, far = ({c: v[at] for c, v in small_batch.items()} for at in (~is_long, is_long))
        changes["main_store"] = _placed_here(ix.main_store, near, usual, segment, ix)
        if long is not None:
            changes["outlier_store"] = _placed_here(ix.outlier_store, far, long, segment, ix)
            changes["stairs"] = staircase.table(rows.sparkSession, *staircase.lowered(*ix.steps, near["zmin"], near["zmax"]))
    else:
        changes["main_store"] = _place(ix.main_store, usual, segment, ix)
        if long is not None:
            changes["outlier_store"] = _place(ix.outlier_store, long, segment, ix)
            changes["stairs"] = settle(staircase.apply_inserts(ix.stairs, usual))
    if upsert:
        changes["tombstones"] = _buried(ix, rows)
    out = ix.evolve(**changes)
    return compact(out) if any(s is not None and len(s.segments) > LOOSE_SEGMENTS for s in (out.main_store, out.outlier_store)) else out


def _buried(ix: ZIndex, rows: DataFrame) -> DataFrame:
    """The tombstones with those of ``rows``; they hide all segments of versions before the next."""
    gone = rows.select("geom_id", "zmin").distinct().withColumn("seq", F.lit(ix.version + 1 << 32).cast("long"))
    return settle(gone if ix.tombstones is None else ix.tombstones.unionByName(gone))


def delete(ix: ZIndex, rows: DataFrame) -> ZIndex:
    """Removes records by (geom_id, zmin): only equal keys within equal codes; boxes and staircase stay, so both loosen."""
    tomb = _buried(ix, rows)
    return ix.evolve(tombstones=tomb, stats={**ix.stats, "loose": ix.stats.get("loose", 0) + tomb.where(F.col("seq") == F.lit(ix.version + 1 << 32)).count()})


def visible(ix: ZIndex) -> DataFrame:
    """All live records."""
    rows = ix.main.select(*_ROW, "seg") if ix.outlier is None else ix.main.select(*_ROW, "seg").unionByName(ix.outlier.select(*_ROW, "seg"))
    return alive(ix, rows).drop("seg")


def _rewritten(ix: ZIndex, store: Store, rows: DataFrame, segment: int) -> Store:
    """``rows`` (with leaf_id and leaf_band) as the store's only segment; positions, models and levels anew."""
    store.append(rows, segment, loose=False)
    fresh = replace(store, segments=(segment,))
    return indexed(store.root, (segment,), store.schema, leaf_directory(fresh.rows, store.key), ix.config, rows.sparkSession)


def compact(ix: ZIndex, cap: int | None = None) -> ZIndex:
    """Cuts leaves over capacity into parts, brings loose rows home and drops deleted ones.

    Leaves that fit keep their id; new ids follow the greatest, one after another. Bands keep their range of keys.
    """
    cap = cap or ix.config.leaf_cap
    segment = ix.next_segment()

    def tidy(store: Store) -> Store:
        home = store.leaves.select("leaf_id", F.col("leaf_band").alias("_band"), "n")
        live = alive(ix, store.rows).drop("leaf_band").join(small(home), "leaf_id").withColumnRenamed("_band", "leaf_band")
        over = live.where(F.col("n") > cap)
        part = F.floor((F.row_number().over(W.partitionBy("leaf_id").orderBy(store.key, "zmax", "geom_id")) - 1) / cap)
        cut = settle(over.withColumn("_part", part))
        top = (store.leaves.agg(F.max("leaf_id")).first()[0] or 0) + 1
        parts = cut.where("_part > 0").groupBy("leaf_id", "_part").count().select("leaf_id", "_part")
        ids = with_rank(parts.repartitionByRange("leaf_id", "_part").sortWithinPartitions("leaf_id", "_part")).select("leaf_id", "_part", (F.col("rank") + top).alias("_new"))
        moved = cut.join(small(ids), ["leaf_id", "_part"], "left").withColumn("leaf_id", F.coalesce("_new", "leaf_id")).drop("_new", "_part")
        return _rewritten(ix, store, live.where(F.col("n") <= cap).unionByName(moved).drop("n"), segment)

    stores = {"main_store": tidy(ix.main_store)}
    if ix.outlier_store is not None:
        stores["outlier_store"] = tidy(ix.outlier_store)
    return ix.evolve(**stores, tombstones=None, stats={**ix.stats, "loose": 0})


def merge_leaves(ix: ZIndex, min_fill: float = 0.25) -> ZIndex:
    """Joins runs of neighbouring leaves of a band until they hold about ``min_fill`` of the capacity; a run is full once
    the count before it passes a multiple of that."""
    least = max(1, int(ix.config.leaf_cap * min_fill))
    before = F.coalesce(F.sum("n").over(W.partitionBy("leaf_band").orderBy("pos").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    runs = ix.leaves.withColumn("_run", F.floor(before / least))
    to = runs.select("leaf_id", F.first("leaf_id").over(W.partitionBy("leaf_band", "_run").orderBy("pos")).alias("_to"), F.col("leaf_band").alias("_band"))
    rows = alive(ix, ix.main).drop("leaf_band").join(small(to), "leaf_id").withColumn("leaf_id", F.col("_to")).withColumn("leaf_band", F.col("_band")).drop("_to", "_band")
    store = _rewritten(ix, ix.main_store, rows, ix.next_segment())
    return ix.evolve(main_store=store)


def maybe_rebuild(ix: ZIndex, checked_per_result: float, ratio: float = 2.0) -> ZIndex:
    """A new index of the live records once searches check ``ratio`` times as many per result as after the last build."""
    was = ix.stats.get("checked_per_result")
    if was is None:
        return replace(ix, stats={**ix.stats, "checked_per_result": checked_per_result})
    if checked_per_result < ratio * was:
        return ix
    fresh = build_index(visible(ix), ix.config)
    fresh.version, fresh.stats, fresh.applied = ix.version + 1, {}, ix.applied
    return fresh


def relaid(ix: ZIndex) -> ZIndex:
    """The staircase anew over the records in place, without a new sort; after deletes and inserts have loosened it."""
    rows = alive(ix, ix.main).join(small_dir(ix.leaves), "leaf_id")
    return ix.evolve(stairs=settle(staircase.build(rows, None, "leaf")))
