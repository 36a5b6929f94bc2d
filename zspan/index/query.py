"""Searching: lower the start, let the base find the leaves of the key range, skip leaves by box, scan, test shapes.

A window is (qid, wx0, wx1, wy0, wy1), a rectangle; zlo and zhi are its interval. Windows of other shapes carry qkind
and qrings too. Searches are planned on the driver where windows, directory and staircase are within their bounds, and by joins
otherwise. Either way the bands and key ranges that are needed reach the scan as literals, so it opens only those folders
and row groups.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from zspan.augment import staircase
from zspan.config import QueryOptions
from zspan.curve.zorder import cell_of_units, z_address
from zspan.geometry import predicates
from zspan.index.build import LOOSE, Store, ZIndex
from zspan.plans import once, settle, small

DEFAULT = QueryOptions()
#: Windows and (window, leaf) hits that the driver plans; key ranges that a scan is given.
PLAN_WINDOWS, PLAN_HITS, KEY_RANGES = 65_536, 4_000_000, 16
_WINDOW = ("qid", "wx0", "wx1", "wy0", "wy1", "zlo", "zhi")


def with_window_interval(windows: DataFrame, units_per_cell: int = 1) -> DataFrame:
    code = lambda x, y: once((x, y, units_per_cell), lambda: z_address(cell_of_units(F.col(x), units_per_cell), cell_of_units(F.col(y), units_per_cell)))
    return windows.withColumns({"zlo": code("wx0", "wy0"), "zhi": code("wx1", "wy1")})


def boxes_meet(a: str = "") -> Column:
    return F.expr(f"{a}x0 <= wx1 and {a}x1 >= wx0 and {a}y0 <= wy1 and {a}y1 >= wy0")


def stores(ix: ZIndex, rel: str) -> Iterator[tuple[str, Store]]:
    """(how its scan starts, store): at the window, through the staircase, or from 0."""
    if rel not in ("contains", "intersects"):
        raise ValueError(f"an index answers contains and intersects, not {rel}")
    if ix.outlier_store is None:
        if rel == "intersects":
            raise ValueError("this index was built without augmentation: it answers contains only")
        yield "window", ix.main_store
    else:
        yield "window" if rel == "contains" else "stairs", ix.main_store
        yield "window" if rel == "contains" else "zero", ix.outlier_store


def with_start(ix: ZIndex, windows: DataFrame, how: str) -> DataFrame:
    if how == "stairs":
        return staircase.augment(windows, ix.stairs)
    return windows.withColumn("zstart", F.col("zlo") if how == "window" else F.lit(0).cast("long"))


# --- planning by joins ---------------------------------------------------------------------------------------------


def leaf_hits(store: Store, windows: DataFrame, leaf_skip: bool = True) -> DataFrame:
    """``windows`` (with zstart) with the leaf_id and leaf_band of the leaves that they must read, by joins.

    The base finds the positions of the last leaf before the start and of the last one not beyond the end; windows meet the
    bands between, a bounded number, and then their leaves by an equi join.
    """
    near = store.base.probe(windows.withColumn("_before", F.col("zstart") - 1), "_before", "pos_lo")
    near = store.base.probe(near, "zhi", "pos_hi").drop("_before")
    bands = F.broadcast(store.bands.select("leaf_band", *[F.col(c).alias("b_" + c) for c in ("pos_lo", "pos_hi", "x0", "y0", "x1", "y1")]))
    meets = (F.col("b_pos_lo") <= F.col("pos_hi")) & (F.col("b_pos_hi") >= F.col("pos_lo"))
    hit = near.join(bands, meets & boxes_meet("b_") if leaf_skip else meets).drop(*[c for c in bands.columns if c != "leaf_band"])
    dir_ = store.leaves.select("leaf_id", "leaf_band", "pos", "first_key", "last_key", "x0", "y0", "x1", "y1")
    own = hit.join(dir_, "leaf_band").where(F.col("pos").between(F.col("pos_lo"), F.col("pos_hi")) & (F.col("first_key") <= F.col("zhi")) & (F.col("last_key") >= F.col("zstart")))
    return (own.where(boxes_meet()) if leaf_skip else own).drop("pos", "pos_lo", "pos_hi", "first_key", "last_key", "x0", "y0", "x1", "y1")


# --- planning on the driver ----------------------------------------------------------------------------------------


def _codes(x: np.ndarray, y: np.ndarray, units: int) -> np.ndarray:
    """``z_address`` of arrays."""
    out = np.zeros(len(x), np.int64)
    x, y = x // units, y // units
    for k in range(31):
        out |= ((x >> k) & 1) << (2 * k) | ((y >> k) & 1) << (2 * k + 1)
    return out


def _collected(windows: DataFrame, units: int = 1) -> dict[str, np.ndarray] | None:
    """The windows as arrays with their intervals, or None beyond the bound."""
    got = windows.select(*[c for c in _WINDOW if c in windows.columns]).limit(PLAN_WINDOWS + 1).toArrow()
    if got.num_rows > PLAN_WINDOWS:
        return None
    w = {c: got.column(c).to_numpy() for c in got.column_names}
    return {"zlo": _codes(w["wx0"], w["wy0"], units), "zhi": _codes(w["wx1"], w["wy1"], units)} | w


def _start_of(ix: ZIndex, how: str, zlo: np.ndarray) -> np.ndarray | None:
    if how == "window":
        return zlo
    if how == "zero":
        return np.zeros_like(zlo)
    if ix.steps is None:
        return None
    ends, values = ix.steps
    if not len(ends):
        return zlo
    at = np.searchsorted(ends, zlo)
    return np.where(at < len(ends), np.minimum(zlo, values[np.minimum(at, len(ends) - 1)]), zlo)


@dataclass(frozen=True)
class Hits:
    """Planned (window, leaf) pairs of one store, as row numbers; and the comparisons of the probes."""

    window: np.ndarray
    leaf: np.ndarray
    start: np.ndarray
    steps: int


def resident_hits(store: Store, w: dict[str, np.ndarray], start: np.ndarray, leaf_skip: bool = True) -> Hits | None:
    """The same as ``leaf_hits`` in arrays, or None beyond the bound."""
    d = store.directory
    if not len(d.leaf_id) or not len(start):
        return Hits(np.zeros(0, np.int64), np.zeros(0, np.int64), start, 0)
    (lo, a), (hi, b) = store.base.locate(start - 1), store.base.locate(w["zhi"])
    out, wins, total = [], [], 0
    for i in range(len(start)):
        own = slice(lo[i], hi[i] + 1)
        meets = (d.first[own] <= w["zhi"][i]) & (d.last[own] >= start[i])
        if leaf_skip:
            x0, y0, x1, y1 = d.box[:, own]
            meets &= (x0 <= w["wx1"][i]) & (x1 >= w["wx0"][i]) & (y0 <= w["wy1"][i]) & (y1 >= w["wy0"][i])
        at = np.flatnonzero(meets) + lo[i]
        out.append(at)
        wins.append(len(at))
        total += len(at)
        if total > PLAN_HITS:
            return None
    return Hits(np.repeat(np.arange(len(start)), wins), np.concatenate(out), start, int(a.sum() + b.sum()))


def _ranges(lo: np.ndarray, hi: np.ndarray, most: int = KEY_RANGES) -> list[tuple[int, int]]:
    """At most ``most`` key ranges that cover all [lo, hi], the widest gaps left out."""
    order = np.argsort(lo)
    lo, reach = lo[order], np.maximum.accumulate(hi[order])
    gaps = np.maximum(lo[1:] - reach[:-1], 0)
    cuts = np.sort(np.argsort(-gaps, kind="stable")[: most - 1])
    cuts = cuts[gaps[cuts] > 1]
    return list(zip(lo[np.r_[0, cuts + 1]].tolist(), reach[np.r_[cuts, len(reach) - 1]].tolist(), strict=True)) if len(lo) else []


def needed(store: Store, bands: list[int], ranges: list[tuple[int, int]]) -> DataFrame:
    """The store's rows in these bands (and loose ones) and key ranges: both conditions reach the files."""
    keys = " or ".join(f"{store.key} between {a} and {b}" for a, b in ranges) or "false"
    return store.rows.where(f"leaf_band in ({', '.join(map(str, (LOOSE, *bands)))}) and ({keys})")


# --- candidates ----------------------------------------------------------------------------------------------------


def planned(ix: ZIndex, windows: DataFrame, rel: str, options: QueryOptions = DEFAULT) -> list[tuple[Store, DataFrame, DataFrame]]:
    """Of each store (store, rows that may be needed, hits): hits are the windows with zstart and leaf_id."""
    units = ix.config.units_per_cell
    fits = options.resident is not False and all(s.directory is not None for _, s in stores(ix, rel))
    w = _collected(windows, units) if fits else None
    out = []
    for how, store in stores(ix, rel):
        start = _start_of(ix, how, w["zlo"]) if w else None
        hits = resident_hits(store, w, start, options.leaf_skip) if start is not None else None
        if hits is not None:
            cols = {c: pa.array(w[c][hits.window]) for c in _WINDOW} | {"zstart": pa.array(start[hits.window]), "leaf_id": pa.array(store.directory.leaf_id[hits.leaf])}
            found = windows.sparkSession.createDataFrame(pa.table(cols))
            more = [c for c in windows.columns if c not in _WINDOW]
            found = found.join(windows.select("qid", *more), "qid") if more else found
            asked = np.unique(hits.window)
            rows = needed(store, np.unique(store.directory.band[hits.leaf]).tolist(), _ranges(start[asked], w["zhi"][asked]))
            found = F.broadcast(found)  # at most PLAN_HITS rows
        else:
            coded = windows if "zlo" in windows.columns else with_window_interval(windows, units)
            found = settle(leaf_hits(store, with_start(ix, coded, how), options.leaf_skip))
            seen = found.groupBy("leaf_band").agg(F.min("zstart").alias("a"), F.max("zhi").alias("b")).toPandas()  # one row a band
            rows = needed(store, seen["leaf_band"].tolist(), _ranges(seen["a"].to_numpy(np.int64), seen["b"].to_numpy(np.int64)))
            found = small(found.drop("leaf_band"))
        out.append((store, rows, found))
    return out


def alive(ix: ZIndex, rows: DataFrame) -> DataFrame:
    """``rows`` (with seg) without those that a later delete names."""
    if ix.tombstones is None:
        return rows
    gone = ix.tombstones.select(F.col("geom_id").alias("_id"), F.col("zmin").alias("_z"), "seq")
    return rows.join(small(gone), (F.col("geom_id") == F.col("_id")) & (F.col("zmin") == F.col("_z")) & (F.col("seq") > F.col("seg")), "left_anti")


def candidates(ix: ZIndex, windows: DataFrame, rel: str, options: QueryOptions = DEFAULT) -> DataFrame:
    """Records that reach the shape test, with their window: the rows of ``records checked``."""
    out = None
    for store, rows, hits in planned(ix, windows, rel, options):
        found = rows.join(hits, "leaf_id").where(f"{store.key} between zstart and zhi")
        found = (found.where(boxes_meet()) if options.mbr_filter else found).drop("leaf_band")
        out = found if out is None else out.unionByName(found, allowMissingColumns=True)
    return alive(ix, out).drop("seg")


def refine(found: DataFrame, rel: str, rectangles: bool = True) -> DataFrame:
    if not rectangles:
        return predicates.refine_general(found, rel)
    w, box = [F.col(c) for c in ("wx0", "wx1", "wy0", "wy1")], tuple(F.col(c) for c in ("x0", "x1", "y0", "y1"))
    if rel == "contains":
        return found.where(once(("contains",), lambda: predicates.contains_rect(F.col("rings"), F.col("kind"), *box, *w)))
    return found.where(boxes_meet()).where(once(("intersects",), lambda: predicates.intersects_rect(F.col("rings"), F.col("kind"), *w, box)))


def range_join(ix: ZIndex, windows: DataFrame, rel: str, options: QueryOptions = DEFAULT, rectangles: bool = True) -> DataFrame:
    """(qid, geom_id) of all windows; exact, no pair twice. ``rel`` touches is what Intersects finds, by general shapes."""
    if rel == "touches":
        return refine(candidates(ix, windows, "intersects", options).where(boxes_meet()), "touches", False).select("qid", "geom_id")
    found = candidates(ix, windows, rel, options)
    return (refine(found, rel, rectangles) if options.refine else found).select("qid", "geom_id")


def late_range_join(ix: ZIndex, windows: DataFrame, rel: str = "intersects") -> DataFrame:
    """``range_join`` that reads shapes for undecided pairs only.

    The first pass reads keys and boxes. A box inside the window decides Intersects; the rest join their shapes by
    (leaf_id, geom_id), again from the bands and key ranges of the windows alone.
    """
    held = (F.col("x0") >= F.col("wx0")) & (F.col("x1") <= F.col("wx1")) & (F.col("y0") >= F.col("wy0")) & (F.col("y1") <= F.col("wy1"))
    out = None
    for store, rows, hits in planned(ix, windows, rel):
        keys = [c for c in rows.columns if c not in ("kind", "rings")]
        found = alive(ix, rows.select(keys).join(hits, "leaf_id").where(F.col(store.key).between(F.col("zstart"), F.col("zhi")) & boxes_meet()))
        pairs = settle(found.select("qid", "geom_id", "seg", "leaf_id", "x0", "y0", "x1", "y1", "wx0", "wx1", "wy0", "wy1", (held & F.lit(rel == "intersects")).alias("sure")))
        open_ = pairs.where(~F.col("sure"))
        shapes = rows.select("leaf_id", "geom_id", "seg", "kind", "rings").join(small(open_), ["leaf_id", "geom_id", "seg"])
        own = pairs.where("sure").select("qid", "geom_id").unionByName(refine(shapes, rel).select("qid", "geom_id"))
        out = own if out is None else out.unionByName(own)
    return out


# --- one window ----------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class LeafPlan:
    """What was decided for one window: keys to scan, leaves and bands to read, leaves that boxes ruled out."""

    zlo: int
    zhi: int
    zstart: int
    leaf_ids: tuple[int, ...]
    bands: tuple[int, ...]
    skipped: int
    steps: int


def _one(spark, window: tuple[int, int, int, int], ix: ZIndex) -> DataFrame:
    return with_window_interval(spark.createDataFrame([(0, *window)], "qid long, wx0 long, wx1 long, wy0 long, wy1 long"), ix.config.units_per_cell)


def plan_leaves(ix: ZIndex, window: tuple[int, int, int, int], rel: str, store: str = "main") -> LeafPlan:
    """The plan for one rectangle (wx0, wx1, wy0, wy1): every leaf in the key range is tested once, the first included."""
    how, own = dict(zip(("main", "outlier"), stores(ix, rel), strict=False))[store]
    spark, units = own.leaves.sparkSession, ix.config.units_per_cell
    w = {c: np.array([v], np.int64) for c, v in zip(("wx0", "wx1", "wy0", "wy1"), window, strict=True)}
    w |= {"zlo": _codes(w["wx0"], w["wy0"], units), "zhi": _codes(w["wx1"], w["wy1"], units)}
    start = _start_of(ix, how, w["zlo"]) if own.directory is not None else None
    if start is None:
        rows = leaf_hits(own, with_start(ix, _one(spark, window, ix), how), False)
        rows = rows.join(own.leaves.select("leaf_id", "x0", "y0", "x1", "y1"), "leaf_id").select("zstart", "leaf_id", "leaf_band", boxes_meet().alias("meets")).collect()  # one window's leaves
        read = [r for r in rows if r["meets"]]
        first = rows[0]["zstart"] if rows else int(w["zlo"][0])
        return LeafPlan(int(w["zlo"][0]), int(w["zhi"][0]), first, tuple(sorted(r["leaf_id"] for r in read)), tuple(sorted({r["leaf_band"] for r in read})), len(rows) - len(read), 0)
    read, every = resident_hits(own, w, start), resident_hits(own, w, start, False)
    d = own.directory
    return LeafPlan(int(w["zlo"][0]), int(w["zhi"][0]), int(start[0]), tuple(sorted(d.leaf_id[read.leaf].tolist())), tuple(np.unique(d.band[read.leaf]).tolist()), len(every.leaf) - len(read.leaf), read.steps)


def range_query(ix: ZIndex, window: tuple[int, int, int, int], rel: str, options: QueryOptions = DEFAULT) -> DataFrame:
    """Rows for one rectangle; leaves, bands and keys are literals of the scan."""
    out = None
    for name, (_, store) in zip(("main", "outlier"), stores(ix, rel), strict=False):
        p = plan_leaves(ix, window, rel, name)
        if options.leaf_skip and not p.leaf_ids:
            continue  # nothing of this store meets the window
        if options.leaf_skip:
            own = store.rows.where(f"leaf_band in ({', '.join(map(str, (LOOSE, *p.bands)))}) and {store.key} between {p.zstart} and {p.zhi} and leaf_id in ({', '.join(map(str, p.leaf_ids))})")
        else:
            own = store.rows.where(f"{store.key} between {p.zstart} and {p.zhi}")
        out = own if out is None else out.unionByName(own, allowMissingColumns=True)
    out = alive(ix, ix.main.where("false") if out is None else out)
    kept = [c for c in out.columns if c not in ("seg", "leaf_band", "leaf_id", "rank")]
    out = out.selectExpr(*kept, *[f"{v}L as {c}" for c, v in zip(("wx0", "wx1", "wy0", "wy1"), window, strict=True)])
    return (refine(out, rel) if options.refine else out).select(*kept)


def disjoint_counts(ix: ZIndex, windows: DataFrame, n: int) -> DataFrame:
    """(qid, apart): how many of ``n`` geometries share no point with a window, without listing them."""
    met = range_join(ix, windows, "intersects").groupBy("qid").agg(F.count("*").alias("met"))
    return windows.select("qid").join(met, "qid", "left").select("qid", (F.lit(n) - F.coalesce("met", F.lit(0))).alias("apart"))


def disjoint(geoms: DataFrame, ix: ZIndex, window: tuple[int, int, int, int]) -> DataFrame:
    """The geometries that share no point with one window: an anti join, as large as the set itself."""
    return geoms.join(range_query(ix, window, "intersects").select("geom_id"), "geom_id", "left_anti")


def explain_query(ix: ZIndex, window: tuple[int, int, int, int], rel: str) -> DataFrame:
    """(store, zlo, zhi, zstart, leaves_read, leaves_skipped, steps) of one window."""
    rows = []
    for name, _ in zip(("main", "outlier"), stores(ix, rel), strict=False):
        p = plan_leaves(ix, window, rel, name)
        rows.append((name, p.zlo, p.zhi, p.zstart, len(p.leaf_ids), p.skipped, p.steps))
    return ix.leaves.sparkSession.createDataFrame(rows, "store string, zlo long, zhi long, zstart long, leaves_read long, leaves_skipped long, steps long")


def locate(ix: ZIndex, keys: DataFrame, key: str = "key", by_joins: bool = False) -> DataFrame:
    """(qid, pos, leaf_id, predicted, slot, steps): the leaf of a key by the base, and its first slot not below the key.

    In the leaf a search gallops from the model's slot to the right one: 2 * ceil(log2(distance + 1)) + 1 comparisons; a
    B-tree halves the whole leaf.
    """
    store = ix.main_store
    if store.directory is not None and not by_joins:
        got = keys.select("qid", key).limit(PLAN_WINDOWS + 1).toArrow()  # beyond the bound: by joins
        if got.num_rows <= PLAN_WINDOWS:
            pos, steps = store.base.locate(got.column(key).to_numpy())
            at = keys.sparkSession.createDataFrame(pa.table({"qid": got.column("qid"), key: got.column(key), "pos": pa.array(pos), "_steps": pa.array(steps)}))
        else:
            at = store.base.probe(keys.select("qid", key), key, "pos").withColumn("_steps", F.lit(0).cast("long"))
    else:
        at = store.base.probe(keys.select("qid", key), key, "pos").withColumn("_steps", F.lit(0).cast("long"))
    found = at.join(store.leaves.select("pos", "leaf_id", "first_key", "n"), "pos").join(ix.leaf_models, "leaf_id")
    guess = F.least(F.greatest(F.round(F.col("intercept") + F.col("slope") * (F.col(key) - F.col("first_key"))), F.lit(0.0)), F.col("n") - 1.0).cast("long")
    found = found.withColumn("predicted", guess)
    before = store.rows.select("leaf_id", F.col(store.key).alias("_k")).join(small(found.select("qid", "leaf_id", key)), "leaf_id").where(F.col("_k") < F.col(key)).groupBy("qid").agg(F.count("*").alias("slot"))
    full = found.join(before, "qid", "left").withColumn("slot", F.coalesce("slot", F.lit(0)))
    inside = F.ceil(F.log2(F.col("n") + 1)) if ix.config.base == "btree" else 2 * F.ceil(F.log2(F.abs(F.col("slot") - F.col("predicted")) + 1)) + 1
    return full.select("qid", "pos", "leaf_id", "predicted", "slot", (F.col("_steps") + inside).cast("long").alias("steps"))
