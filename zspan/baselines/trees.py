"""The index's rivals: sort-tile R-tree, quad-tree, block summaries, cell grid and the plain scan.

Each search returns (qid, geom_id) for rectangles after the same exact test, and has a form that counts what it checks. The
trees keep their nodes on the driver as the index keeps its directory, up to the same bound, and search, insert and delete as
it does. Beyond the bound the quad-tree keeps its quadrants in a table; ``rtree`` and ``rtree_candidates`` are the R-tree by
joins of level tables, without a bound.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zspan.curve.zorder import z_decode
from zspan.index.build import RESIDENT_LEAVES, box_of
from zspan.index.query import boxes_meet, refine, with_window_interval
from zspan.plans import settle, small, with_rank

_WINDOW = ("qid", "wx0", "wx1", "wy0", "wy1")
_BOX = ("x0", "y0", "x1", "y1")


def scan(geoms: DataFrame, windows: DataFrame, rel: str) -> DataFrame:
    """Every geometry against every window."""
    return refine(F.broadcast(windows).crossJoin(geoms), rel).select("qid", "geom_id")


# --- R-tree by joins -----------------------------------------------------------------------------------------------


def tiled(geoms: DataFrame, cap: int) -> DataFrame:
    """``geoms`` with the leaf node of sort-tile packing: strips by x centre, runs of ``cap`` by y centre."""
    n = geoms.count()
    slices = max(1, math.ceil(math.sqrt(math.ceil(n / cap))))
    per = max(1, math.ceil(n / slices))
    cx, cy = F.col("x0") + F.col("x1"), F.col("y0") + F.col("y1")
    across = geoms.withColumn("_cx", cx).repartitionByRange("_cx", "geom_id").sortWithinPartitions("_cx", "geom_id")
    strips = with_rank(across).withColumn("strip", F.floor(F.col("rank") / per)).drop("_cx", "rank", "part", "at")
    nth = F.row_number().over(W.partitionBy("strip").orderBy(cy, "geom_id")) - 1
    return settle(strips.withColumn("node", (F.col("strip") * math.ceil(per / cap) + F.floor(nth / cap)).cast("long")).drop("strip"))


def rtree(geoms: DataFrame, cap: int = 16) -> list[DataFrame]:
    """Levels: [entries with node, then (node, parent, box) up to one root]."""
    level = tiled(geoms, cap)
    out, boxes = [level], level.groupBy("node").agg(*box_of())
    while True:
        boxes = settle(boxes.withColumn("parent", F.floor(F.col("node") / cap).cast("long")))
        out.append(boxes)
        if boxes.count() <= 1:
            return out
        boxes = boxes.groupBy(F.col("parent").alias("node")).agg(*box_of())


def rtree_candidates(levels: list[DataFrame], windows: DataFrame) -> DataFrame:
    """Entries whose own box meets the window, found from the root by one join a level."""
    w = small(windows)
    hit = w.join(levels[-1].select("node", *_BOX), boxes_meet()).select("qid", F.col("node").alias("parent"))
    for level in reversed(levels[1:-1]):
        hit = level.join(hit, "parent").join(w, "qid").where(boxes_meet()).select("qid", F.col("node").alias("parent"))
    return levels[0].join(hit.withColumnRenamed("parent", "node"), "node").join(w, "qid").where(boxes_meet())


# --- trees with resident nodes -------------------------------------------------------------------------------------


def _windows(windows: DataFrame) -> dict[str, np.ndarray]:
    got = windows.select(*_WINDOW).toArrow()  # the experiments' windows, a hundred
    return {c: got.column(c).to_numpy() for c in _WINDOW}


def _hits(windows: DataFrame, w: dict[str, np.ndarray], found: list[np.ndarray], **cols: np.ndarray) -> DataFrame:
    """(window, node columns) as a table, for node numbers found per window."""
    which, at = np.repeat(np.arange(len(found)), [len(x) for x in found]), np.concatenate(found) if found else np.zeros(0, np.int64)
    table = {c: pa.array(w[c][which]) for c in _WINDOW} | {c: pa.array(v[at]) for c, v in cols.items()}
    return small(windows.sparkSession.createDataFrame(pa.table(table)))


def _alive(rows: DataFrame, gone: DataFrame | None) -> DataFrame:
    if gone is None:
        return rows
    dead = gone.select(F.col("geom_id").alias("_id"), "seq")
    return rows.join(small(dead), (F.col("geom_id") == F.col("_id")) & (F.col("seq") > F.col("seg")), "left_anti")


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _meets(box: np.ndarray, w: dict[str, np.ndarray], i: int) -> np.ndarray:
    return (box[0] <= w["wx1"][i]) & (box[2] >= w["wx0"][i]) & (box[1] <= w["wy1"][i]) & (box[3] >= w["wy0"][i])


@dataclass(frozen=True)
class RTree:
    """Entries by leaf node on files; boxes and counts of all nodes on the driver, packed level by level."""

    parts: list[DataFrame]  # geom columns, node, seg
    box: np.ndarray  # of leaf nodes, by number
    n: np.ndarray
    cap: int = 16
    gone: DataFrame | None = None
    seq: int = 0
    levels: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list, repr=False)  # bottom up: (children in order, box)

    @classmethod
    def fit(cls, geoms: DataFrame, cap: int = 16) -> RTree:
        rows = tiled(geoms, cap).withColumn("seg", F.lit(0))
        got = rows.groupBy("node").agg(F.count("*").alias("n"), *box_of()).limit(RESIDENT_LEAVES + 1).toPandas().sort_values("node")
        if len(got) > RESIDENT_LEAVES:
            raise ValueError("too many nodes for the driver: use rtree and rtree_candidates")
        size = int(got["node"].max()) + 1 if len(got) else 0
        n, box = np.zeros(size, np.int64), np.zeros((4, size), np.int64)
        box[:2], box[2:] = np.iinfo(np.int64).max // 2, np.iinfo(np.int64).min // 2
        n[got["node"]] = got["n"]
        for i, c in enumerate(_BOX):
            box[i, got["node"]] = got[c]
        return cls([rows], box, n, cap).packed()

    def packed(self) -> RTree:
        """Upper levels anew, by sort-tile packing of the boxes of nodes in use."""
        out, ids = [], np.flatnonzero(self.box[0] <= self.box[2])
        box = self.box[:, ids]
        while box.shape[1] > 1 or (box.shape[1] and not out):
            m = box.shape[1]
            slices = max(1, math.ceil(math.sqrt(math.ceil(m / self.cap))))
            strip = np.empty(m, np.int64)
            strip[np.argsort(box[0] + box[2], kind="stable")] = np.arange(m) // math.ceil(m / slices)
            order = np.lexsort((box[1] + box[3], strip))
            own, cuts = box[:, order], np.arange(0, m, self.cap)
            out.append((order if out else ids[order], own))
            box = np.stack([np.minimum.reduceat(own[0], cuts), np.minimum.reduceat(own[1], cuts), np.maximum.reduceat(own[2], cuts), np.maximum.reduceat(own[3], cuts)])
        return replace(self, levels=out)

    def nodes_of(self, w: dict[str, np.ndarray], i: int) -> np.ndarray:
        """Leaf nodes whose box meets window ``i``, from the root down."""
        at = np.zeros(1, np.int64)
        for order, box in reversed(self.levels):
            kids = (at[:, None] * self.cap + np.arange(self.cap)).ravel()
            kids = kids[kids < len(order)]
            at = order[kids[_meets(box[:, kids], w, i)]]
        return at if self.levels else at[:0]

    def candidates(self, windows: DataFrame) -> DataFrame:
        w = _windows(windows)
        found = [self.nodes_of(w, i) for i in range(len(w["qid"]))]
        hits = _hits(windows, w, found, node=np.arange(self.box.shape[1]))
        return _alive(_union(self.parts).join(hits, "node").where(boxes_meet()), self.gone)

    def search(self, windows: DataFrame, rel: str) -> DataFrame:
        return refine(self.candidates(windows), rel).select("qid", "geom_id")

    def chosen(self, boxes: np.ndarray) -> np.ndarray:
        """For each box (4, k) the leaf node whose ancestors and itself grow least in area, ties to the smaller one."""
        k = boxes.shape[1]
        at = np.zeros(k, np.int64)
        area = lambda b: (b[2] - b[0]).astype(float) * (b[3] - b[1])
        for order, box in reversed(self.levels):
            kids = at[:, None] * self.cap + np.arange(self.cap)
            own = np.minimum(kids, len(order) - 1)
            b = box[:, own]
            grown = np.stack([np.minimum(b[0], boxes[0][:, None]), np.minimum(b[1], boxes[1][:, None]), np.maximum(b[2], boxes[2][:, None]), np.maximum(b[3], boxes[3][:, None])])
            cost = np.where(kids < len(order), area(grown) - area(b), np.inf)
            best = np.argmin(np.where(cost <= cost.min(1)[:, None], area(b), np.inf), 1)
            at = order[own[np.arange(k), best]]
        return at

    def insert(self, rows: DataFrame) -> RTree:
        """Rows go to the node that grows least; boxes grow, and nodes over capacity are halved along their longer side."""
        shared = rows.sparkSession.sparkContext.broadcast(replace(self, parts=[], gone=None))

        @F.pandas_udf("long")
        def node(x0, y0, x1, y1):
            import pandas as pd

            return pd.Series(shared.value.chosen(np.stack([c.to_numpy(np.int64) for c in (x0, y0, x1, y1)])))

        seq = self.seq + 1
        new = settle(rows.withColumn("node", node(*_BOX)).withColumn("seg", F.lit(seq)).select(self.parts[0].columns))
        got = new.groupBy("node").agg(F.count("*").alias("n"), *box_of()).toPandas()  # one row a touched node
        n, box, at = self.n.copy(), self.box.copy(), got["node"].to_numpy(np.int64)
        n[at] += got["n"].to_numpy(np.int64)
        for i, c in enumerate(_BOX):
            box[i, at] = (np.minimum if i < 2 else np.maximum)(box[i, at], got[c].to_numpy(np.int64))
        out = replace(self, parts=[*self.parts, new], n=n, box=box, seq=seq)
        full = np.flatnonzero(n > self.cap)
        return out.split(full) if len(full) else out.packed()

    def split(self, full: np.ndarray) -> RTree:
        spark = self.parts[0].sparkSession
        over = F.broadcast(spark.createDataFrame(pa.table({"node": pa.array(full)})))  # within the nodes' bound
        every = _alive(_union(self.parts), self.gone)
        own = every.join(over, "node")
        wide = F.max("x1").over(W.partitionBy("node")) - F.min("x0").over(W.partitionBy("node")) >= F.max("y1").over(W.partitionBy("node")) - F.min("y0").over(W.partitionBy("node"))
        centre = F.when(F.col("_wide"), F.col("x0") + F.col("x1")).otherwise(F.col("y0") + F.col("y1"))
        half = F.floor((F.row_number().over(W.partitionBy("node").orderBy(centre, "geom_id")) - 1) * F.ceil(F.count("*").over(W.partitionBy("node")) / self.cap) / F.count("*").over(W.partitionBy("node")))
        cut = settle(own.withColumn("_wide", wide).withColumn("_half", half).drop("_wide"))
        ids = cut.select("node", "_half").distinct().toPandas().sort_values(["node", "_half"])
        fresh = ids["_half"].to_numpy(np.int64) > 0
        ids["new"] = np.where(fresh, len(self.n) - 1 + np.cumsum(fresh), ids["node"])
        named = spark.createDataFrame(pa.table({"node": pa.array(ids["node"].to_numpy(np.int64)), "_half": pa.array(ids["_half"].to_numpy(np.int64)), "_new": pa.array(ids["new"].to_numpy(np.int64))}))
        moved = settle(cut.join(F.broadcast(named), ["node", "_half"]).withColumn("node", F.col("_new")).select(self.parts[0].columns))
        kept = every.join(over, "node", "left_anti").select(self.parts[0].columns)
        got = moved.groupBy("node").agg(F.count("*").alias("n"), *box_of()).toPandas()
        more = int(fresh.sum())
        n, box = np.r_[self.n, np.zeros(more, np.int64)], np.concatenate([self.box, np.zeros((4, more), np.int64)], 1)
        at = got["node"].to_numpy(np.int64)
        n[at] = got["n"]
        for i, c in enumerate(_BOX):
            box[i, at] = got[c]
        return replace(self, parts=[settle(kept.unionByName(moved))], n=n, box=box, gone=None).packed()

    def delete(self, rows: DataFrame) -> RTree:
        """Entries are found by their boxes from the root down, and taken out of their nodes; boxes stay, as in the index."""
        shared = rows.sparkSession.sparkContext.broadcast(replace(self, parts=[], gone=None))

        @F.pandas_udf("array<long>")
        def nodes(x0, y0, x1, y1):
            import pandas as pd

            w = {"wx0": x0.to_numpy(), "wx1": x1.to_numpy(), "wy0": y0.to_numpy(), "wy1": y1.to_numpy()}
            return pd.Series([shared.value.nodes_of(w, i) for i in range(len(x0))])

        asked = rows.select("geom_id", F.explode(nodes(*_BOX)).alias("node"))
        found = _alive(_union(self.parts), self.gone).select("geom_id", "node").join(asked, ["geom_id", "node"])
        seq = self.seq + 1
        gone = settle(found.select("geom_id", "node").withColumn("seq", F.lit(seq)))
        lost = gone.groupBy("node").count().toPandas()
        n = self.n.copy()
        n[lost["node"].to_numpy(np.int64)] -= lost["count"].to_numpy(np.int64)
        return replace(self, n=n, gone=settle(gone.drop("node") if self.gone is None else self.gone.unionByName(gone.drop("node"))), seq=seq)

    def size_bytes(self) -> int:
        """40 bytes for every entry and every node, at all levels."""
        return 40 * int(self.n.sum() + (self.n > 0).sum() + sum(box.shape[1] for _, box in self.levels[1:]) + (1 if self.levels else 0))


def quadrant(max_level: int = 20, bits: int = 30) -> tuple[Column, Column]:
    """(level, code) of the smallest quadrant that holds a box, from the corner codes: their common prefix."""
    differ = F.col("zmin").bitwiseXOR(F.col("zmax"))
    used = F.when(differ == 0, 0).otherwise(F.length(F.bin(differ)))
    level = F.least(F.lit(bits) - F.ceil(used / 2), F.lit(max_level)).cast("long")
    return level, F.expr(f"shiftright(zmin, cast(2 * ({bits} - level) as int))")


def quadtree(geoms: DataFrame, max_level: int = 20, bits: int = 30) -> DataFrame:
    """Records with their quadrant (level, code)."""
    level, code = quadrant(max_level, bits)
    return geoms.withColumn("level", level).withColumn("code", code)


def _squares(quads: DataFrame, bits: int = 30) -> DataFrame:
    lo = F.expr(f"shiftleft(code, cast(2 * ({bits} - level) as int))")
    hi = F.expr(f"shiftleft(code + 1, cast(2 * ({bits} - level) as int)) - 1")
    (x0, y0), (x1, y1) = z_decode(lo), z_decode(hi)
    return quads.select("level", "code", x0.alias("x0"), y0.alias("y0"), x1.alias("x1"), y1.alias("y1"))


@dataclass(frozen=True)
class Quadtree:
    """Records by quadrant on files; the occupied quadrants and their squares on the driver, up to RESIDENT_LEAVES of them.

    Beyond that bound ``quads`` and ``box`` are None: a table holds the quadrants, and windows find them by a join with the
    table's (level, code).
    """

    parts: list[DataFrame]  # geom columns, level, code, seg
    quads: np.ndarray | None  # level, code
    box: np.ndarray | None
    gone: DataFrame | None = None
    seq: int = 0
    taken: DataFrame | None = None  # (level, code) and square of each occupied quadrant, where the driver does not hold them

    @staticmethod
    def _taken(rows: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
        got = _squares(rows.select("level", "code").distinct()).limit(RESIDENT_LEAVES + 1).toArrow()
        if got.num_rows > RESIDENT_LEAVES:
            return None
        return tuple(np.stack([got.column(c).to_numpy().astype(np.int64) for c in cols]) for cols in (("level", "code"), _BOX))

    @classmethod
    def _placed(cls, parts: list[DataFrame]) -> dict:
        """What holds the quadrants of ``parts``: the driver, or beyond its bound a table."""
        every = _union(parts).select("level", "code").distinct()
        got = cls._taken(every)
        if got is None:
            return {"quads": None, "box": None, "taken": settle(_squares(every))}
        return {"quads": got[0], "box": got[1], "taken": None}

    @classmethod
    def fit(cls, geoms: DataFrame) -> Quadtree:
        rows = settle(quadtree(geoms).withColumn("seg", F.lit(0)).repartitionByRange("level", "code").sortWithinPartitions("level", "code"))
        return cls([rows], **cls._placed([rows]))

    def candidates(self, windows: DataFrame) -> DataFrame:
        """Records in quadrants whose square meets the window."""
        if self.quads is None:
            hits = small(windows.select(*_WINDOW)).join(self.taken, boxes_meet()).select(*_WINDOW, "level", "code")
        else:
            w = _windows(windows)
            found = [np.flatnonzero(_meets(self.box, w, i)) for i in range(len(w["qid"]))]
            hits = _hits(windows, w, found, level=self.quads[0], code=self.quads[1])
        return _alive(_union(self.parts).join(hits, ["level", "code"]), self.gone)

    def search(self, windows: DataFrame, rel: str) -> DataFrame:
        return refine(self.candidates(windows).where(boxes_meet()), rel).select("qid", "geom_id")

    def insert(self, rows: DataFrame) -> Quadtree:
        new = settle(quadtree(rows).withColumn("seg", F.lit(self.seq + 1)).select(self.parts[0].columns))
        parts = [*self.parts, new]
        if len(parts) > 16:
            parts = [settle(_union(parts).repartitionByRange("level", "code").sortWithinPartitions("level", "code"))]
        fresh = self._taken(new) if self.quads is not None else None
        if fresh is not None:
            both, which = np.unique(np.concatenate([self.quads, fresh[0]], 1), axis=1, return_index=True)
            if both.shape[1] <= RESIDENT_LEAVES:
                return replace(self, parts=parts, quads=both, box=np.concatenate([self.box, fresh[1]], 1)[:, which], seq=self.seq + 1)
        return replace(self, **self._placed(parts), parts=parts, seq=self.seq + 1)

    def delete(self, rows: DataFrame) -> Quadtree:
        """Records are found in their quadrant, and taken out."""
        asked = quadtree(rows.select("geom_id", "zmin", "zmax")).select("geom_id", "level", "code")
        found = _alive(_union(self.parts), self.gone).select("geom_id", "level", "code").join(asked, ["level", "code", "geom_id"])
        gone = found.select("geom_id").withColumn("seq", F.lit(self.seq + 1))
        return replace(self, gone=settle(gone if self.gone is None else self.gone.unionByName(gone)), seq=self.seq + 1)

    def size_bytes(self) -> int:
        """40 bytes for every record and every occupied quadrant."""
        quads = self.taken.count() if self.quads is None else self.quads.shape[1]
        return 40 * (quads + sum(p.count() for p in self.parts))


# --- summaries and cells -------------------------------------------------------------------------------------------


def zonemap(ranked: DataFrame, block_rows: int = 1024) -> DataFrame:
    """Boxes of blocks of rows in storage order (by geom_id rank): (block, n, box)."""
    return ranked.groupBy(F.floor(F.col("rank") / block_rows).alias("block")).agg(F.count("*").alias("n"), *box_of())


def zonemap_query(ranked: DataFrame, blocks: DataFrame, windows: DataFrame, rel: str, block_rows: int = 1024) -> DataFrame:
    hits = small(windows).join(blocks, boxes_meet()).select("block", *windows.columns)
    own = ranked.withColumn("block", F.floor(F.col("rank") / block_rows))
    return refine(own.join(hits, "block"), rel).select("qid", "geom_id")


def histogram(geoms: DataFrame, cells: int = 16, width: int = 720_000_000, height: int = 360_000_000) -> DataFrame:
    """(bx, by, n): counts of box centres in equal-width buckets, the coarsest summary of where the data lies."""
    bucket = lambda a, b, side: F.width_bucket(((F.col(a) + F.col(b)) / 2).cast("double"), F.lit(0.0), F.lit(float(side)), F.lit(cells)).cast("long")
    return geoms.groupBy(bucket("x0", "x1", width).alias("bx"), bucket("y0", "y1", height).alias("by")).agg(F.count("*").alias("n"))


def grid(geoms: DataFrame, side: int) -> DataFrame:
    """A record for each square cell that a geometry's box touches: the duplicates that intervals avoid."""
    cells = lambda a, b: F.sequence(F.floor(F.col(a) / side), F.floor(F.col(b) / side))
    return geoms.withColumn("gx", F.explode(cells("x0", "x1"))).withColumn("gy", F.explode(cells("y0", "y1")))


def grid_query(cells: DataFrame, windows: DataFrame, rel: str, side: int) -> DataFrame:
    w = windows.withColumn("gx", F.explode(F.sequence(F.floor(F.col("wx0") / side), F.floor(F.col("wx1") / side)))).withColumn("gy", F.explode(F.sequence(F.floor(F.col("wy0") / side), F.floor(F.col("wy1") / side))))
    found = cells.join(w, ["gx", "gy"]).where(boxes_meet()).dropDuplicates(["qid", "geom_id"])
    return refine(found, rel).select("qid", "geom_id")


def interval_only(geoms: DataFrame, windows: DataFrame, rel: str) -> DataFrame:
    """Candidates by interval alone, without shapes: what an index that only probes would return."""
    from zspan.interval import z_contains, z_overlaps

    w = with_window_interval(windows)
    test = (z_contains if rel == "contains" else z_overlaps)(F.col("zlo"), F.col("zhi"), F.col("zmin"), F.col("zmax"))
    return small(w).join(geoms, test).select("qid", "geom_id")
