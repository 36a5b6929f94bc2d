"""Well-known binary of points, lines and polygons, as open table formats carry it; numbers are whole units."""

from __future__ import annotations

import struct

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from zspan.geometry.model import RINGS

# Geometry codes of the format.
_KINDS = {1: "POINT", 2: "LINESTRING", 3: "POLYGON"}


def parse(data: bytes) -> tuple[str, list[list[tuple[int, int]]]]:
    order = "<" if data[0] == 1 else ">"
    (code,) = struct.unpack_from(order + "I", data, 1)
    at = 5

    def ring(n: int) -> list[tuple[int, int]]:
        nonlocal at
        flat = struct.unpack_from(f"{order}{2 * n}d", data, at)
        at += 16 * n
        return [(int(x), int(y)) for x, y in zip(flat[::2], flat[1::2], strict=True)]

    def count() -> int:
        nonlocal at
        (n,) = struct.unpack_from(order + "I", data, at)
        at += 4
        return n

    kind = _KINDS[code]
    if kind == "POINT":
        return kind, [ring(1)]
    if kind == "LINESTRING":
        return kind, [ring(count())]
    return kind, [ring(count()) for _ in range(count())]


def pack(kind: str, rings) -> bytes:
    code = {v: k for k, v in _KINDS.items()}[kind]
    body = lambda r: b"".join(struct.pack("<2d", float(p["x"]), float(p["y"])) for p in r)
    out = struct.pack("<BI", 1, code)
    if kind == "POINT":
        return out + body(rings[0])
    if kind == "LINESTRING":
        return out + struct.pack("<I", len(rings[0])) + body(rings[0])
    return out + struct.pack("<I", len(rings)) + b"".join(struct.pack("<I", len(r)) + body(r) for r in rings)


_PARSED = T.StructType([T.StructField("kind", T.StringType()), T.StructField("rings", RINGS)])


def read(df: DataFrame, col: str) -> DataFrame:
    """Adds kind and rings of a binary column."""

    @F.pandas_udf(_PARSED)
    def parsed(c: pd.Series) -> pd.DataFrame:
        got = [parse(bytes(x)) if x else (None, None) for x in c]
        return pd.DataFrame({"kind": [k for k, _ in got], "rings": [None if r is None else [[{"x": x, "y": y} for x, y in one] for one in r] for _, r in got]})

    return df.withColumn("_g", parsed(F.col(col))).withColumns({"kind": F.col("_g.kind"), "rings": F.col("_g.rings")}).drop("_g")


def write(df: DataFrame, col: str = "wkb") -> DataFrame:
    """Adds the binary form of kind and rings."""

    @F.pandas_udf(T.BinaryType())
    def packed(kind: pd.Series, rings: pd.Series) -> pd.Series:
        return pd.Series([pack(k, r) for k, r in zip(kind, rings, strict=True)])

    return df.withColumn(col, packed("kind", "rings"))
