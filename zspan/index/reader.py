"""One window against a saved index, read with Arrow alone: for tasks, which have no session.

Directory, staircase and stores are read by their files' statistics, so a task opens the row groups that the window asks for
and keeps one batch at a time. Only the staircase's piece and the window's own leaf ids are held.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
from pyarrow import fs

from zspan.geometry.predicates import _ROUND_KINDS, relation
from zspan.index.build import LOOSE
from zspan.index.query import _codes

Window = tuple[int, int, int, int]
_BOX = ("x0", "x1", "y0", "y1")


def located(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(path if ":" in path else f"file://{path}")


def latest(path: str) -> dict:
    """The manifest of the last saved version."""
    store, root = located(path)
    lines = [x for p in store.get_file_info(fs.FileSelector(f"{root}/manifest")) if p.path.endswith(".txt") for x in store.open_input_stream(p.path).read().decode().splitlines()]
    return max((json.loads(x) for x in lines), key=lambda m: m["version"])


def _batches(path: str, columns: list[str], where: ds.Expression) -> Iterator[pa.RecordBatch]:
    """Batches of a folder of Parquet files; none where it holds no file."""
    store, root = located(path)
    data = ds.dataset(root, filesystem=store, format="parquet", partitioning="hive")
    if data.files:
        yield from data.to_batches(columns=columns, filter=where)


def _start(m: dict, zlo: int) -> int:
    """The staircase's start for a scan from ``zlo``: that of the first piece that reaches it."""
    best = None
    for b in _batches(m["stairs"], ["hi_incl", "start_key"], ds.field("hi_incl") >= zlo):
        if b.num_rows:
            k = int(np.argmin(b.column("hi_incl").to_numpy()))
            piece = b.column("hi_incl")[k].as_py(), b.column("start_key")[k].as_py()
            best = piece if best is None else min(best, piece)
    return zlo if best is None else min(zlo, best[1])


def _meets(w: Window) -> ds.Expression:
    return (ds.field("x0") <= w[1]) & (ds.field("x1") >= w[0]) & (ds.field("y0") <= w[3]) & (ds.field("y1") >= w[2])


def plan(path: str, window: Window, rel: str) -> Iterator[tuple[str, int, int, int, int]]:
    """(store, zstart, zhi, leaf_band, leaf_id) of the leaves that a rectangle (wx0, wx1, wy0, wy1) has to read."""
    m = latest(path)
    if rel not in ("contains", "intersects"):
        raise ValueError(f"an index answers contains and intersects, not {rel}")
    if rel == "intersects" and "outlier" not in m:
        raise ValueError("this index was built without augmentation: it answers contains only")
    units = m["config"]["units_per_cell"]
    zlo, zhi = (int(_codes(np.array([x]), np.array([y]), units)[0]) for x, y in ((window[0], window[2]), (window[1], window[3])))
    for name in ("main", "outlier"):
        if name in m:
            start = zlo if rel == "contains" else 0 if name == "outlier" else _start(m, zlo)
            reached = (ds.field("first_key") <= zhi) & (ds.field("last_key") >= start) & _meets(window)
            for b in _batches(m[name]["leaves"], ["leaf_band", "leaf_id"], reached):
                yield from ((name, start, zhi, r["leaf_band"], r["leaf_id"]) for r in b.to_pylist())


def _buried(m: dict, batch: pa.RecordBatch, seg: int) -> set[tuple[int, int]]:
    """Those (geom_id, zmin) of a batch that a later delete names."""
    if "tombstones" not in m or not batch.num_rows:
        return set()
    z = pc.min_max(batch.column("zmin")).as_py()
    later = (ds.field("seq") > seg) & (ds.field("zmin") >= z["min"]) & (ds.field("zmin") <= z["max"]) & ds.field("geom_id").isin(batch.column("geom_id"))
    return {(r["geom_id"], r["zmin"]) for b in _batches(m["tombstones"], ["geom_id", "zmin"], later) for r in b.to_pylist()}


def search(path: str, window: Window, rel: str) -> Iterator[tuple]:
    """(geom_id, kind, x0, x1, y0, y1) of one rectangle's exact result, batch by batch."""
    m, (wx0, wx1, wy0, wy1) = latest(path), window
    if rel == "contains" and (wx0 == wx1 or wy0 == wy1):
        return  # no area, nothing within
    leaves: dict[str, list] = {}
    for name, *rest in plan(path, window, rel):
        leaves.setdefault(name, []).append(rest)
    ring = [[{"x": x, "y": y} for x, y in ((wx0, wy0), (wx1, wy0), (wx1, wy1), (wx0, wy1), (wx0, wy0))]]
    key = m["config"]["sort_key"]
    for name, found in leaves.items():
        start, zhi = found[0][:2]
        bands, ids = sorted({LOOSE, *(f[2] for f in found)}), sorted({f[3] for f in found})
        asked = ds.field("leaf_band").isin(bands) & ds.field("leaf_id").isin(ids) & (ds.field(key) >= start) & (ds.field(key) <= zhi) & _meets(window)
        for seg in m[name]["segments"]:
            for b in _batches(f"{m[name]['root']}/seg={seg}", ["geom_id", "zmin", "kind", *_BOX, "rings"], asked):
                gone = _buried(m, b, seg)
                x0, x1, y0, y1 = (b.column(c).to_numpy() for c in _BOX)
                held = (x0 >= wx0) & (x1 <= wx1) & (y0 >= wy0) & (y1 <= wy1)
                within = (x0 > wx0) & (x1 < wx1) & (y0 > wy0) & (y1 < wy1)
                area = pc.is_in(b.column("kind"), pa.array(_ROUND_KINDS)).to_numpy(zero_copy_only=False)
                sure = held if rel == "intersects" else held & (area | within)  # else: a line or point that may lie on the border alone
                open_ = ~held if rel == "intersects" else held & ~sure
                for i in np.flatnonzero(open_):
                    sure[i] = relation(rel, "POLYGON", ring, b.column("kind")[i].as_py(), b.column("rings")[i].as_py())
                found = b.select(["geom_id", "zmin", "kind", *_BOX]).filter(pa.array(sure))
                for i, z, *rest in zip(*(c.to_pylist() for c in found.columns), strict=True):
                    if (i, z) not in gone:
                        yield i, *rest
