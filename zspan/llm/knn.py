"""Exact top-k inner-product search over KD-trees, one tree per shard.

Shards are cells of median splits of a bounded sample, so that vectors of a shard lie together; a cell with more vectors
than a shard holds, such as one of equal vectors, is dealt further by a hash of the id. A shard's tree splits at medians of
the widest component and keeps a tight box for every node. A query walks a tree best-first: the node whose box allows the
highest inner product comes next, and the walk ends when no remaining box can beat the k-th result so far. Blocks of
queries meet blocks of the shards' own boxes first. Each query searches the shard of its highest bound, then the next best ones
with the k-th result found, and then every shard whose bound the k-th result still does not beat; pairs of a query and a shard
that it rules out are dropped before any shuffle.

Rows with a null or non-finite component, no component or a null id take no part. Repeated ids count once, with their
smallest vector. Vectors are compared with vectors of the same length only. Ties go to the smaller id. Scaled components
beyond 2^62 count as that, and scores beyond the range of a long as its limit.
"""

from __future__ import annotations

import heapq
import io

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from zspan.llm.common import map_batches, written
from zspan.plans import small

#: Vectors of a shard and of a tree's leaf; queries that meet a shard in one task; vectors that place the splits, about;
#: shards whose boxes meet a block of queries in one task.
SHARD_ROWS, LEAF_ROWS, BLOCK_ROWS, SAMPLE, BOXES = 8192, 256, 4096, 65_536, 512
_LONG = 2**63 - 1
_EXACT = 2**52


def quantise(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 64) -> DataFrame:
    """Valid rows as (vec_id long, v array<long>), components as floor(scale * x) of x as double."""
    x = F.col(vec_col)
    fine = x.isNotNull() & (F.size(x) > 0) & F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c.cast("double")) & (F.abs(c.cast("double")) < float("inf")))
    most = F.lit(float(2**62))
    v = F.transform(x, lambda c: F.floor(F.greatest(F.least(c.cast("double") * F.lit(float(scale)), most), -most)).cast("long"))
    return df.where(F.col(id_col).isNotNull() & fine).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).groupBy("vec_id").agg(F.min("v").alias("v"))


def build_tree(ids: np.ndarray, vectors: np.ndarray, leaf_rows: int = LEAF_ROWS) -> dict[str, np.ndarray]:
    """Nodes in preorder; a node's vectors are rows start..end of the reordered arrays; right = 0 marks a leaf."""
    order = np.argsort(ids, kind="stable")
    start, end, right, lo, hi, least = [], [], [], [], [], []

    def grow(a: int, b: int) -> int:
        me, own = len(start), vectors[order[a:b]]
        low, high = own.min(0), own.max(0)
        start.append(a), end.append(b), right.append(0), lo.append(low), hi.append(high), least.append(ids[order[a:b]].min())
        axis = int(np.argmax(high - low))
        if b - a > leaf_rows:
            mid = (b - a) // 2
            if high[axis] > low[axis]:
                order[a:b] = order[a:b][np.argpartition(own[:, axis], mid)]
            grow(a, a + mid)
            right[me] = grow(a + mid, b)
        return me

    grow(0, len(ids))
    return {"ids": ids[order], "v": vectors[order], "start": np.array(start), "end": np.array(end), "right": np.array(right), "lo": np.array(lo), "hi": np.array(hi), "least": np.array(least)}


def search_tree(tree: dict[str, np.ndarray], qids: np.ndarray, queries: np.ndarray, k: int, kth: list[tuple[int, int] | None]) -> list[list[tuple[int, int]]]:
    """For each query the (score, id) that beat its ``kth`` (score, id), best first, k at most."""
    peak = max(np.abs(tree["v"]).max(initial=1), 1) * float(max(np.abs(queries).max(initial=1), 1)) * queries.shape[1]
    kind = np.float64 if peak < _EXACT else np.int64 if peak < 2**62 else object
    v, q, lo, hi = (x.astype(kind) for x in (tree["v"], queries, tree["lo"], tree["hi"]))
    bounds = np.maximum(q, 0) @ hi.T + np.minimum(q, 0) @ lo.T
    ids, start, end, right, least = tree["ids"], tree["start"].tolist(), tree["end"].tolist(), tree["right"].tolist(), tree["least"].tolist()
    out = []
    for i, own in enumerate(qids.tolist()):
        bound, best, bar = bounds[i].tolist(), [], kth[i]
        if kind is object:
            bound = [max(-_LONG, min(_LONG, x)) for x in bound]
        todo = [(-bound[0], least[0], 0)]
        while todo:
            top, first, node = heapq.heappop(todo)
            if bar is not None and (-top < bar[0] or (-top == bar[0] and first > bar[1])):
                break
            if right[node]:
                for child in (node + 1, right[node]):
                    heapq.heappush(todo, (-bound[child], least[child], child))
                continue
            a, b = start[node], end[node]
            score = v[a:b] @ q[i]
            if kind is object:
                score = np.array([max(-_LONG, min(_LONG, x)) for x in score], object)
            near = np.nonzero(score >= bar[0])[0] if bar is not None else np.arange(b - a)
            if not len(near):
                continue
            pairs = list(zip(score[near].tolist(), ids[a:b][near].tolist(), strict=True))
            best = heapq.nsmallest(k, best + [p for p in pairs if p[1] != own and (bar is None or p[0] > bar[0] or p[1] < bar[1])], key=lambda p: (-p[0], p[1]))
            if len(best) == k:
                bar = best[-1] if bar is None or (best[-1][0], -best[-1][1]) > (bar[0], -bar[1]) else bar
        out.append(best)
    return out


def _pack(tree: dict[str, np.ndarray]) -> bytes:
    np.savez(buf := io.BytesIO(), **tree)
    return buf.getvalue()


def split_cells(sample: np.ndarray, cells: int) -> list[tuple[int, int, int, int]]:
    """Median splits of a sample into about ``cells`` parts: nodes (axis, threshold, left, right), -1 - cell for a cell."""
    nodes: list[tuple[int, int, int, int]] = []
    made = 0

    def grow(own: np.ndarray, want: int) -> int:
        nonlocal made
        spread = own.max(0) - own.min(0) if len(own) else np.zeros(1)
        axis = int(np.argmax(spread))
        if want < 2 or len(own) < 2 or spread[axis] == 0:
            made += 1
            return -made
        at = int(np.sort(own[:, axis])[len(own) // 2])
        at = at if (own[:, axis] < at).any() else int(own[:, axis][own[:, axis] > at].min())
        me = len(nodes)
        nodes.append((axis, at, 0, 0))
        low = own[:, axis] < at
        left, right = grow(own[low], want // 2), grow(own[~low], want - want // 2)
        nodes[me] = (axis, at, left, right)
        return me

    grow(sample, cells)
    return nodes


def cell_of(nodes: list[tuple[int, int, int, int]], v: np.ndarray) -> np.ndarray:
    """The cell of each vector, from 0."""
    at = np.zeros(len(v), np.int64) if nodes else np.full(len(v), -1)
    while (open_ := np.flatnonzero(at >= 0)).size:
        for n in np.unique(at[open_]):
            axis, least, left, right = nodes[n]
            own = open_[at[open_] == n]
            at[own] = np.where(v[own, axis] < least, left, right)
    return -1 - at


def _bounds(q: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """An upper bound of every query's inner products in every box, as doubles that are never too low."""
    q, lo, hi = (x.astype(np.float64) for x in (q, lo, hi))
    found = np.maximum(q, 0) @ hi.T + np.minimum(q, 0) @ lo.T
    size = np.abs(q) @ np.maximum(np.abs(lo), np.abs(hi)).T
    return found + size * 1e-12 + 1e-6


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 20, shard_rows: int = SHARD_ROWS, leaf_rows: int = LEAF_ROWS, block_rows: int = BLOCK_ROWS, visited: list[int] | None = None) -> DataFrame:
    """The ``k`` highest inner products of each query among all other vectors: query_id, rank, vec_id, score.

    ``vectors`` and ``queries`` are (vec_id, v) as ``quantise`` gives them. ``visited`` receives the number of (query, shard)
    pairs that each wave searches.
    """
    spark = vectors.sparkSession
    vectors = written(vectors.select("vec_id", "v", F.size("v").alias("dim")), "vectors")
    sizes = {r["dim"]: r["n"] for r in vectors.groupBy("dim").agg(F.count("*").alias("n")).collect()}  # one row a length of vectors
    total = sum(sizes.values())
    picked = vectors.where(F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(max(1, total))) < SAMPLE).toPandas()  # bounded: SAMPLE of all, about
    cells = {d: split_cells(np.stack(own["v"].to_numpy()), -(-sizes[d] // shard_rows)) for d, own in picked.groupby("dim")}
    shared = spark.sparkContext.broadcast(cells)  # at most one split a sampled vector

    def deal(batches):
        for b in batches:
            dims, v = b.column("dim").to_numpy(), b.column("v")
            cell = np.zeros(len(dims), np.int64)
            for d in np.unique(dims):
                own = np.flatnonzero(dims == d)
                cell[own] = cell_of(shared.value.get(int(d), []), v.take(pa.array(own)).values.to_numpy().reshape(-1, d))
            yield {"vec_id": b.column("vec_id"), "v": v, "dim": dims, "cell": cell}

    dealt = written(map_batches(vectors, deal, "vec_id long, v array<long>, dim int, cell long"), "dealt")
    parts = dealt.groupBy("dim", "cell").agg(F.ceil(F.count("*") / shard_rows).alias("parts"))
    sharded = dealt.join(small(parts), ["dim", "cell"]).withColumn("part", F.pmod(F.xxhash64("vec_id"), F.col("parts")))

    def plant(pdf: pd.DataFrame) -> pd.DataFrame:
        v = np.stack(pdf["v"].to_numpy())
        tree = build_tree(pdf["vec_id"].to_numpy(), v, leaf_rows)
        return pd.DataFrame({"dim": [v.shape[1]], "cell": [pdf["cell"].iloc[0]], "part": [pdf["part"].iloc[0]], "lo": [v.min(0)], "hi": [v.max(0)], "tree": [_pack(tree)]})

    planted = sharded.groupBy("dim", "cell", "part").applyInPandas(plant, "dim int, cell long, part long, lo array<long>, hi array<long>, tree binary")
    number = F.shiftleft("cell", 24) + F.col("part")
    trees = written(planted.withColumn("shard", number), "trees")
    chunks = max(1, -(-total // (shard_rows * BOXES)))
    boxes = trees.select("dim", "shard", "lo", "hi", F.pmod(F.xxhash64("shard"), F.lit(chunks)).cast("int").alias("chunk"))
    blocks = max(1, -(-queries.count() // block_rows))
    q = written(queries.select("vec_id", "v", F.size("v").alias("dim"), F.pmod(F.xxhash64("vec_id", F.lit(7)), F.lit(blocks)).cast("int").alias("block")), "queries")
    grid = boxes.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def rank(beyond: int):
        def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
            if not len(left) or not len(right):
                return pd.DataFrame({"vec_id": [], "shard": [], "bound": []}).astype({"vec_id": "int64", "shard": "int64", "bound": "float64"})
            bound = _bounds(np.stack(left["v"].to_numpy()), np.stack(right["lo"].to_numpy()), np.stack(right["hi"].to_numpy()))
            order = np.argsort(-bound, axis=1, kind="stable")[:, :beyond] if beyond else None
            bar = left["bar"].to_numpy(float)
            keep = bound >= np.where(np.isnan(bar), -np.inf, bar)[:, None]
            if order is not None:
                top = np.zeros_like(keep)
                np.put_along_axis(top, order, True, 1)
                keep &= top
            i, j = np.nonzero(keep)
            return pd.DataFrame({"vec_id": left["vec_id"].to_numpy()[i], "shard": right["shard"].to_numpy()[j], "bound": bound[i, j]})

        return run

    def pairs(asked: DataFrame, beyond: int) -> DataFrame:
        """(vec_id, shard, bound) of queries (with bar) and shards that the bar does not rule out; of each chunk the best ``beyond``."""
        keys = ("dim", "chunk", "block")
        return asked.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.lit(chunks - 1)))).groupBy(*keys).cogroup(grid.groupBy(*keys)).applyInPandas(rank(beyond), "vec_id long, shard long, bound double")

    found = "query_id long, vec_id long, score long"

    def visit(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        tree = dict(np.load(io.BytesIO(right["tree"].iloc[0])))
        bars = [None if pd.isna(s) else (int(s), int(i)) for s, i in zip(left["kth"], left["kth_id"], strict=True)]
        qids = left["vec_id"].to_numpy()
        rows = [(own, i, int(s)) for own, hits in zip(qids.tolist(), search_tree(tree, qids, np.stack(left["v"].to_numpy()), k, bars), strict=True) for s, i in hits]
        return pd.DataFrame(rows, columns=["query_id", "vec_id", "score"]).astype("int64")

    hits: DataFrame | None = None
    seen: DataFrame | None = None
    none = F.lit(None).cast("decimal(20,0)")
    asked = q.withColumns({"kth": none, "kth_id": none, "bar": F.lit(None).cast("double")})
    for most in (1, 4, 0):  # shards of a wave; 0: all that are left
        open_ = pairs(asked, most)
        if seen is not None:
            open_ = open_.join(seen, ["vec_id", "shard"], "left_anti")
        if most:
            open_ = open_.withColumn("r", F.row_number().over(W.partitionBy("vec_id").orderBy(F.desc("bound"), "shard"))).where(F.col("r") <= most)
        wave = written(open_.select("vec_id", "shard"), "wave")
        if visited is not None:
            visited.append(wave.count())
        side = wave.join(asked, "vec_id").select("vec_id", "v", "dim", "block", "kth", "kth_id", "shard")
        needed = trees.join(side.select("dim", "shard", "block").distinct(), ["dim", "shard"]).select(*[F.col(c).alias(c) for c in ("dim", "shard", "block", "tree")])
        new = written(side.groupBy("dim", "shard", "block").cogroup(needed.groupBy("dim", "shard", "block")).applyInPandas(visit, found), "hits")
        hits = new if hits is None else hits.unionByName(new)
        best = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        hits = hits.withColumn("rank", best.cast("int")).where(F.col("rank") <= k)
        if not most:
            return hits.select("query_id", "rank", "vec_id", "score")
        hits = written(hits.select("query_id", "vec_id", "score"), "best")
        seen = wave if seen is None else seen.unionByName(wave)
        kth = hits.groupBy("query_id").agg(F.count("*").alias("n"), F.min(F.struct("score", -F.col("vec_id"))).alias("w")).where(F.col("n") >= k)
        asked = q.join(kth, q["vec_id"] == kth["query_id"], "left").select(q["*"], F.col("w.score").cast("decimal(20,0)").alias("kth"), (-F.col("w.col2")).cast("decimal(20,0)").alias("kth_id"), F.col("w.score").cast("double").alias("bar"))
