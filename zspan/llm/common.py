"""Helpers shared by the corpus operators."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from zspan.plans import forget, shared_dir, written  # noqa: F401


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[dict]], schema: str | StructType) -> DataFrame:
    """``mapInArrow`` for functions that yield dicts of columns, in the order of ``schema``.

    Workers serve many tasks; at the end of each they give back what its batches took.
    """
    spark_schema = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(spark_schema)

    def run(batches):
        for cols in fn(batches):
            yield pa.RecordBatch.from_arrays([pa.array(cols[f.name], type=f.type) for f in arrow], schema=arrow)
        cols = None
        give_back()

    return df.mapInArrow(run, spark_schema)


def give_back() -> None:
    """Returns freed memory to the system, which allocators would keep for the worker's next task."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of one C library only
    if trim:
        trim(0)


def row_slices(batches: Iterator[pa.RecordBatch], most: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in runs of at most ``most`` rows, not copied."""
    for b in batches:
        for a in range(0, b.num_rows, most):
            yield b.slice(a, most)


def strings(batch: pa.RecordBatch, name: str) -> list[str]:
    """A string column as Python strings, null as the empty string."""
    return [x or "" for x in batch.column(name).to_pylist()]


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def is_held_out(doc_id) -> F.Column:
    """Rows kept away from every fit: crc32 of the id as text leaves remainder 1 by 3."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def text_slices(texts: list[str], most: int = 2_000_000) -> Iterator[tuple[int, int]]:
    """Ranges of ``texts`` with at most ``most`` characters each, or a single text."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield start, i
            start, size = i, 0
        size += len(t) + 1
    if start < len(texts):
        yield start, len(texts)
