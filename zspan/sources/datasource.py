"""``spark.read.format("zspan")``: a saved index's main store, read only where keys ask for it.

Options: path (of the index), store (main or outlier), zlo and zhi. Filters that compare keys or boxes narrow the files further.
Deleted records that no compaction has dropped are still read.
"""

from __future__ import annotations

import functools
import operator
from collections.abc import Iterator

import pyarrow.dataset as ds
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from zspan.geometry.model import RINGS
from zspan.index import reader

_LONGS = ("geom_id", "x0", "y0", "x1", "y1", "zmin", "zmax", "zlen", "leaf_id")
SCHEMA = T.StructType([*(T.StructField(c, T.LongType()) for c in _LONGS), T.StructField("kind", T.StringType()), T.StructField("rings", RINGS)])
_COMPARE = {GreaterThan: operator.gt, GreaterThanOrEqual: operator.ge, LessThan: operator.lt, LessThanOrEqual: operator.le, EqualTo: operator.eq}


class ZspanSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "zspan"

    def schema(self) -> T.StructType:
        return SCHEMA

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return ZspanReader(dict(self.options), schema)


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class ZspanReader(DataSourceReader):
    def __init__(self, options: dict[str, str], schema: T.StructType):
        self.root, self.columns, self.store = options["path"], schema.names, options.get("store", "main")
        self.asked = [("zmin", operator.ge, int(options.get("zlo", 0))), ("zmin", operator.le, int(options.get("zhi", (1 << 63) - 1)))]

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        """Comparisons of whole numbers, keys and boxes alike, narrow the files; the rest goes back."""
        for f in filters:
            compare = _COMPARE.get(type(f))
            if compare and len(f.attribute) == 1 and f.attribute[0] in _LONGS and f.value is not None:
                self.asked.append((f.attribute[0], compare, f.value))
            else:
                yield f

    def _own(self) -> ds.Expression:
        return functools.reduce(operator.and_, (compare(ds.field(c), v) for c, compare, v in self.asked))

    def partitions(self) -> list[_File]:
        """Files whose row groups can hold what was asked for, by their statistics."""
        store, root = reader.located(self.root)
        latest = reader.latest(self.root)[self.store]
        own, out = self._own(), []
        for k in latest["segments"]:
            data = ds.dataset(f"{root}/{self.store}/seg={k}", filesystem=store, format="parquet")
            out += [_File(f.path) for f in data.get_fragments(own) if f.subset(own).row_groups]
        return out

    def read(self, partition: _File):
        store, _ = reader.located(self.root)
        yield from ds.dataset(partition.path, filesystem=store, format="parquet").to_batches(columns=self.columns, filter=self._own())


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # the reader narrows its files by filters
    spark.dataSource.register(ZspanSource)
