"""Where tables are cut, and how large a table may be before it is broadcast or held by the driver."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable

from pyspark import SparkContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []
#: Planned bytes up to which a table gets a broadcast hint.
BROADCAST_BYTES = 64 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or on a local master a temporary one."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir: driver and executors need a shared folder")
    if not _OWN:
        keep = tempfile.TemporaryDirectory(prefix="zspan-")
        atexit.register(keep.cleanup)
        _OWN.append("file://" + keep.name)
    return _OWN[0]


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/zspan/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str = "table") -> DataFrame:
    """Write ``df`` as a table of the shared folder and read it again: its lineage ends there, and filters reach the files."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._zspan_path = path
    return out


def settle(df: DataFrame) -> DataFrame:
    """``df`` computed once; later plans start at its files."""
    return written(df, "settled")


def forget(df: DataFrame) -> None:
    """Delete a table made by ``written`` that no later plan reads."""
    path = getattr(df, "_zspan_path", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


_COLUMNS: dict[tuple, Column] = {}


def once(key: tuple, make: Callable[[], Column]) -> Column:
    """A long expression built once for the running JVM: building one takes a call a node."""
    key = (id(SparkContext._gateway), *key)
    if key not in _COLUMNS:
        _COLUMNS[key] = make()
    return _COLUMNS[key]


def planned_bytes(df: DataFrame) -> int:
    """The optimiser's size of ``df``: real file sizes for tables, upper estimates for what is derived from them."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def small(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """``df`` with a broadcast hint if its planned size allows it, else as it is: the engine then shuffles both sides."""
    return F.broadcast(df) if planned_bytes(df) <= most else df


def cover(keys: DataFrame, key: str, pieces: DataFrame, lo: str, hi: str, shift: int, how: str = "left") -> DataFrame:
    """``keys`` joined to the piece (``lo``, ``hi``], bounds included by ``hi`` only, that holds ``key``.

    An equi join on blocks of 2^``shift`` keys: a piece is listed under every block that it covers, so neither side has to
    be small. Pieces don't overlap.
    """
    blocks = F.sequence(F.shiftright(F.col(lo) + 1, shift), F.shiftright(F.col(hi), shift))
    listed = pieces.withColumn("_block", F.explode(blocks))
    inside: Column = (F.col(key) > F.col(lo)) & (F.col(key) <= F.col(hi)) & (F.col("_key_block") == F.col("_block"))
    return keys.withColumn("_key_block", F.shiftright(F.col(key), shift)).join(listed, inside, how).drop("_key_block", "_block")


def with_rank(ordered: DataFrame) -> DataFrame:
    """A settled, range-partitioned table with its global rank: position in the partition plus the rows before it.

    One count per partition travels through the driver; no row passes through a single task. Columns part and at name the
    partition and the place there; ``_zspan_rows`` of the result is the number of rows.
    """
    at = F.monotonically_increasing_id()
    placed = settle(ordered.withColumns({"part": F.shiftright(at, 33).cast("long"), "at": at.bitwiseAND(F.lit((1 << 33) - 1))}))
    counts = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}
    before, total = [], 0
    for p in range(max(counts, default=-1) + 1):
        before.append(total)
        total += counts.get(p, 0)
    offset = F.element_at(F.lit(before), F.col("part").cast("int") + 1) if before else F.lit(0)
    out = placed.withColumn("rank", (offset + F.col("at")).cast("long"))
    out._zspan_rows = total
    return out
