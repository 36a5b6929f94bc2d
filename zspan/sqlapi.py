"""Functions for SQL users: codes, box tests, the key ranges of a window, plans and searches of a saved index."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from zspan.geometry.predicates import _general
from zspan.index import reader

_M = (0x0000FFFF0000FFFF, 0x00FF00FF00FF00FF, 0x0F0F0F0F0F0F0F0F, 0x3333333333333333, 0x5555555555555555)


def _spread(v: str) -> str:
    """Nested shift-and-mask text; each round reads its input twice, so inputs pass through subqueries."""
    out = f"(SELECT {v} AS v0)"
    for k, (shift, mask) in enumerate(zip((16, 8, 4, 2, 1), _M, strict=True)):
        out = f"(SELECT (v{k} | shiftleft(v{k}, {shift})) & {mask}L AS v{k + 1} FROM {out})"
    return f"(SELECT v5 FROM {out})"


def ranges(x0: int, y0: int, x1: int, y1: int, most: int = 16, bits: int = 30) -> list[tuple[int, int]]:
    """At most ``most`` code intervals that together cover a box and lie within its interval."""
    todo, done = [(0, 0, bits)], []
    while todo:
        todo.sort(key=lambda q: -q[2])
        x, y, k = todo.pop(0)
        side = 1 << k
        if x > x1 or y > y1 or x + side - 1 < x0 or y + side - 1 < y0:
            continue
        inside = x >= x0 and y >= y0 and x + side - 1 <= x1 and y + side - 1 <= y1
        if inside or k == 0 or len(todo) + len(done) + 4 > most:
            lo = sum(((x >> b & 1) << 2 * b) | ((y >> b & 1) << 2 * b + 1) for b in range(bits))
            done.append((lo, lo + (1 << 2 * k) - 1))
        else:
            h = side // 2
            todo += [(x, y, k - 1), (x + h, y, k - 1), (x, y + h, k - 1), (x + h, y + h, k - 1)]
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(done):
        if out and lo <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(hi, out[-1][1]))
        else:
            out.append((lo, hi))
    return out


class _Ranges:
    def eval(self, x0: int, y0: int, x1: int, y1: int, most: int):
        yield from ranges(x0, y0, x1, y1, most)


class _Plan:
    def eval(self, path: str, wx0: int, wx1: int, wy0: int, wy1: int, rel: str):
        yield from reader.plan(path, (wx0, wx1, wy0, wy1), rel)


class _Search:
    def eval(self, path: str, wx0: int, wx1: int, wy0: int, wy1: int, rel: str):
        yield from reader.search(path, (wx0, wx1, wy0, wy1), rel)


def _relation(rel: str):
    def test(qkind: pa.Array, qrings: pa.Array, kind: pa.Array, rings: pa.Array) -> pa.Array:
        return _general(pa.array([rel] * len(kind)), qkind, qrings, kind, rings)

    return test


def register(spark: SparkSession) -> None:
    """Temporary functions z_address, z_overlaps, z_contains, zspan_contains, zspan_intersects, zspan_touches, zspan_disjoint (of
    a window's and a geometry's kind and rings); table functions z_ranges, and zspan_plan and zspan_search (path of a saved
    index, wx0, wx1, wy0, wy1, contains or intersects), which run one window a task: many windows go through LATERAL."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION z_address(x BIGINT, y BIGINT) RETURNS BIGINT RETURN {_spread('x')} | shiftleft({_spread('y')}, 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION z_overlaps(qlo BIGINT, qhi BIGINT, glo BIGINT, ghi BIGINT) RETURNS BOOLEAN RETURN qlo <= ghi AND glo <= qhi")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION z_contains(qlo BIGINT, qhi BIGINT, glo BIGINT, ghi BIGINT) RETURNS BOOLEAN RETURN glo >= qlo AND ghi <= qhi")
    for rel in ("contains", "intersects", "touches", "disjoint"):
        spark.udf.register(f"zspan_{rel}", F.arrow_udf(_relation(rel), "boolean"))
    spark.udtf.register("z_ranges", udtf(_Ranges, returnType="lo bigint, hi bigint"))
    spark.udtf.register("zspan_plan", udtf(_Plan, returnType="store string, zstart bigint, zhi bigint, leaf_band bigint, leaf_id bigint"))
    spark.udtf.register("zspan_search", udtf(_Search, returnType="geom_id bigint, kind string, x0 bigint, x1 bigint, y0 bigint, y1 bigint"))
