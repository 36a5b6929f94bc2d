"""Costs and accuracy: counts per window, sizes, prices, times, distributions and model errors."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zspan.config import QueryOptions
from zspan.index.build import ZIndex
from zspan.index.query import candidates, planned, range_join
from zspan.plans import with_rank

# Dollars per GB-month of storage, per hour of memory, per GB moved, by tier.
STORAGE_PRICE, MEMORY_PRICE, TRANSFER_PRICE = {1: 0.08, 2: 0.10, 3: 0.12}, {32: 0.16, 64: 0.33, 128: 0.66}, {"internal 1": 0.01, "internal 2": 0.02, "external": 0.09}


def _per_window(windows: DataFrame, rows: DataFrame, name: str) -> DataFrame:
    """A count for each window, 0 where there is no row."""
    got = rows.groupBy("qid").agg(F.count("*").alias(name))
    return windows.select("qid").join(got, "qid", "left").select("qid", F.coalesce(name, F.lit(0)).alias(name))


def records_checked(ix: ZIndex, windows: DataFrame, rel: str, leaf_skip: bool = True, resident: bool | None = None) -> DataFrame:
    """(qid, checked): records that reach the shape test."""
    return _per_window(windows, candidates(ix, windows, rel, QueryOptions(leaf_skip=leaf_skip, resident=resident)), "checked")


def false_positives(ix: ZIndex, windows: DataFrame, rel: str) -> DataFrame:
    """(qid, checked, results, false_positives)."""
    both = records_checked(ix, windows, rel).join(_per_window(windows, range_join(ix, windows, rel), "results"), "qid")
    return both.withColumn("false_positives", F.col("checked") - F.col("results"))


def leaves_visited(ix: ZIndex, windows: DataFrame, rel: str) -> DataFrame:
    """(qid, visited, skipped) over all stores."""
    out = None
    for skip in (True, False):
        for _, _, hits in planned(ix, windows, rel, QueryOptions(leaf_skip=skip)):
            seen = hits.select("qid", F.lit(int(skip)).alias("v"))
            out = seen if out is None else out.unionByName(seen)
    got = out.groupBy("qid").agg(F.sum("v").alias("visited"), (F.sum(1 - F.col("v")) - F.sum("v")).alias("skipped"))
    return windows.select("qid").join(got, "qid", "left").select("qid", F.coalesce("visited", F.lit(0)).alias("visited"), F.coalesce("skipped", F.lit(0)).alias("skipped"))


def selectivity(results: DataFrame, windows: DataFrame, n: int) -> DataFrame:
    return _per_window(windows, results, "results").withColumn("per_million", F.floor(F.col("results") * 1_000_000 / F.lit(n)))


def start_gap(windows: DataFrame, exact: DataFrame, augmented: DataFrame) -> DataFrame:
    """(qid, gap): how far below the exact lowest start the staircase begins; 0 where nothing reaches the window."""
    both = augmented.join(exact, "qid", "left")
    return windows.select("qid").join(both.select("qid", (F.least("zlo", F.coalesce("lowest", "zlo")) - F.col("zstart")).alias("gap")), "qid")


def index_bytes(ix: ZIndex) -> DataFrame:
    """(part, bytes): structure only, and what the (key, id) entries add."""
    own = ix.base.size_bytes()
    n_main, n_out = ix.main.count(), ix.outlier.count() if ix.outlier is not None else 0
    rows = [("inner", own["inner"]), ("leaves", own["leaves"])]
    if ix.stairs is not None:
        rows += [("staircase", 16 * ix.stairs.count()), ("outlier_leaves", 72 * ix.outlier_leaves.count())]
    rows += [("entries", 16 * (n_main + n_out))]
    return ix.leaves.sparkSession.createDataFrame(rows, "part string, bytes long")


def structure_bytes(ix: ZIndex) -> int:
    """Inner nodes, leaf metadata, staircase and the outliers' leaves, without the entries."""
    return index_bytes(ix).where("part <> 'entries'").agg(F.sum("bytes")).first()[0]


def data_bytes(geoms: DataFrame) -> int:
    """Bytes of the shapes themselves: an id and two numbers a vertex, 8 bytes each."""
    return geoms.agg(F.sum(8 + 16 * F.size(F.flatten("rings")))).first()[0] or 0


def overhead(methods: dict[str, int], data: int, spark) -> DataFrame:
    """(method, bytes, per_mille): structure against data."""
    return spark.createDataFrame([(m, b, 1000 * b // max(1, data)) for m, b in methods.items()], "method string, bytes long, per_mille long")


def file_bytes(df: DataFrame) -> int:
    """Bytes of the files behind a file-based table."""
    return df.select("_metadata.file_path", "_metadata.file_size").distinct().agg(F.sum("file_size")).first()[0] or 0


def monthly_price(size_bytes: int, tier: int) -> float:
    return size_bytes / 1e9 * STORAGE_PRICE[tier]


def memory_price(size_bytes: int) -> float:
    """Dollars an hour of the least memory tier that holds the structure; the largest if none does."""
    return MEMORY_PRICE[next((gb for gb in sorted(MEMORY_PRICE) if size_bytes <= gb * 10**9), max(MEMORY_PRICE))]


def transfer_price(size_bytes: int, route: str) -> float:
    return size_bytes / 1e9 * TRANSFER_PRICE[route]


def cdf(df: DataFrame, col: str, points: int = 1000) -> DataFrame:
    """(nth, value): the value at evenly spaced ranks, from a sketch."""
    shares = [(i + 1) / points for i in range(points)]
    got = df.agg(F.percentile_approx(col, F.lit(shares), 10_000).alias("v"))
    return got.select(F.posexplode("v").alias("nth", "value"))


def cdf_exact(df: DataFrame, col: str, points: int = 100) -> DataFrame:
    """(nth, value) at ranks ceil(nth * N / points), nth from 1."""
    n = df.count()
    ranked = with_rank(df.select(col).repartitionByRange(col).sortWithinPartitions(col)).withColumn("r", F.col("rank") + 1)
    marks = df.sparkSession.createDataFrame([(i, -(-i * n // points)) for i in range(1, points + 1)], "nth long, r long")
    return ranked.join(F.broadcast(marks), "r").select("nth", F.col(col).alias("value"))


def measure(fn: Callable[[], DataFrame]) -> dict[str, float]:
    """Seconds to plan and to run a query into no sink."""
    t0 = time.perf_counter()
    df = fn()
    t1 = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return {"plan_s": t1 - t0, "run_s": time.perf_counter() - t1}


def query_phases(ix: ZIndex, windows: DataFrame, rel: str) -> dict[str, float]:
    """Seconds of probing (start, leaves, candidates) and of the shape test on top."""
    probe = measure(lambda: range_join(ix, windows, rel, QueryOptions(refine=False)))["run_s"]
    whole = measure(lambda: range_join(ix, windows, rel))["run_s"]
    return {"probe_s": probe, "refine_s": max(0.0, whole - probe), "response_s": whole}


def search_steps(models: DataFrame) -> DataFrame:
    """(leaf_id, max_err, steps): probes of an exponential search from the model's guess."""
    return models.select("leaf_id", "max_err", (2 * F.ceil(F.log2(F.col("max_err") + 1)) + 1).cast("long").alias("steps"))
