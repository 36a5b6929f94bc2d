"""Maintenance and mixed workloads: half loaded at once, the rest in batches, with queries between.

A method is anything with ``search(windows, rel)``, ``insert(rows)`` and ``delete(rows)``: the index itself (``Indexed``) and
its rivals in ``baselines.trees``. Queries that follow each other run as one batch, as nothing changes between them.
"""

from __future__ import annotations

import time
from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zspan.baselines.trees import Quadtree, RTree
from zspan.config import IndexConfig
from zspan.index import maintain
from zspan.index.build import ZIndex, build_index
from zspan.index.query import range_join
from zspan.workloads.windows import arrival, is_bulk, transactions


class Method(Protocol):
    def search(self, windows: DataFrame, rel: str) -> DataFrame: ...
    def insert(self, rows: DataFrame) -> Method: ...
    def delete(self, rows: DataFrame) -> Method: ...


@dataclass(frozen=True)
class Indexed:
    ix: ZIndex

    def search(self, windows: DataFrame, rel: str) -> DataFrame:
        return range_join(self.ix, windows, rel)

    def insert(self, rows: DataFrame) -> Indexed:
        return Indexed(maintain.insert(self.ix, rows))

    def delete(self, rows: DataFrame) -> Indexed:
        return Indexed(maintain.delete(self.ix, rows))


@dataclass(frozen=True)
class Done:
    """A transaction, or a run of queries: what it read or wrote, and its seconds."""

    op: str
    step: int
    transactions: int
    records: int
    seconds: float


def loaded(method: str, geoms: DataFrame, cfg: IndexConfig) -> Method:
    if method == "rtree":
        return RTree.fit(geoms)
    if method == "quadtree":
        return Quadtree.fit(geoms)
    from dataclasses import replace

    return Indexed(build_index(geoms, replace(cfg, base={"linear": "adaptive_linear", "btree": "btree"}[method])))


def batch_no(n: int) -> F.Column:
    """The batch in which a record that is not loaded at once arrives."""
    return F.pmod(F.floor(arrival() / 100), F.lit(n))


def batches(geoms: DataFrame, n: int) -> list[DataFrame]:
    """The rows that are not loaded at once, in ``n`` batches by order of arrival."""
    late = geoms.where(~is_bulk())
    return [late.where(batch_no(n) == i) for i in range(n)]


def after_inserts(geoms: DataFrame, cfg: IndexConfig, n: int = 10, method: str = "linear") -> tuple[Method, list[Done]]:
    got, log = loaded(method, geoms.where(is_bulk()), cfg), []
    for i, b in enumerate(batches(geoms, n)):
        rows, t = b.count(), time.perf_counter()
        got = got.insert(b)
        log.append(Done("insert", i, 1, rows, time.perf_counter() - t))
    return got, log


def after_deletes(geoms: DataFrame, cfg: IndexConfig, n: int = 1, method: str = "linear") -> tuple[Method, list[Done]]:
    got, log = loaded(method, geoms, cfg), []
    for i, b in enumerate(batches(geoms, n)):
        rows, t = b.count(), time.perf_counter()
        got = got.delete(b)
        log.append(Done("delete", i, 1, rows, time.perf_counter() - t))
    return got, log


def hybrid(geoms: DataFrame, windows: DataFrame, cfg: IndexConfig, read_share: float, inserts: int = 50, method: str = "linear") -> tuple[Method, list[Done], DataFrame]:
    """Runs the plan. Returns the last index, the log, and (step, qid, rows): the results of each query transaction."""
    got, log, waiting = loaded(method, geoms.where(is_bulk()), cfg), [], batches(geoms, inserts)
    qids = sorted(r["qid"] for r in windows.select("qid").collect())  # a hundred
    plan, reads, found = transactions(read_share, inserts), 0, []
    at = 0
    spark = geoms.sparkSession
    while at < len(plan):
        step, op = plan[at]
        if op == "insert":
            rows = waiting.pop(0)
            n, t = rows.count(), time.perf_counter()
            got = got.insert(rows)
            log.append(Done("insert", step, 1, n, time.perf_counter() - t))
            at += 1
            continue
        run = [s for s, o in plan[at:] if o == "query"][: next((i for i, (_, o) in enumerate(plan[at:]) if o == "insert"), len(plan) - at)]
        for a in range(0, len(run), len(qids)):  # a window can be asked once in a batch
            steps = run[a : a + len(qids)]
            asked = spark.createDataFrame([(qids[(reads + i) % len(qids)], s) for i, s in enumerate(steps)], "qid long, step long")
            t = time.perf_counter()
            hits = got.search(windows.join(F.broadcast(asked.select("qid")), "qid"), "intersects").groupBy("qid").agg(F.count("*").alias("rows")).toPandas()  # one row a window
            log.append(Done("query", steps[0], len(steps), int(hits["rows"].sum()), time.perf_counter() - t))
            counts = dict(zip(hits["qid"].tolist(), hits["rows"].tolist(), strict=True))
            found += [(s, qids[(reads + i) % len(qids)], counts.get(qids[(reads + i) % len(qids)], 0)) for i, s in enumerate(steps)]
            reads += len(steps)
        at += len(run)
    return got, log, spark.createDataFrame(found, "step long, qid long, rows long")


def throughput(log: list[Done], op: str | None = None, first: bool = False) -> float:
    """Records (of one operation) or transactions (of all) a second, the first entry left out as warm-up."""
    own = [x for x in log if op in (None, x.op)]
    rest = own if first or len(own) < 2 else own[1:]
    return sum(x.records if op else x.transactions for x in rest) / max(1e-9, sum(x.seconds for x in rest))
