"""Trajectories from an event stream, and an index that grows batch by batch."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from zspan.config import IndexConfig
from zspan.geometry.mbr import with_mbr
from zspan.index import storage
from zspan.index.build import ZIndex, build_index
from zspan.index.maintain import delete, insert
from zspan.index.query import range_join
from zspan.interval import with_zinterval
from zspan.plans import new_path, settle
from zspan.sources.fixtures import water_vertices


def _instants(events: DataFrame) -> DataFrame:
    """``events`` with ``at``, the instant of ts; a ts without zone is read as UTC."""
    ts = F.col("ts")
    if events.schema["ts"].dataType.simpleString() == "timestamp_ntz":
        ts = F.convert_timezone(F.lit("UTC"), F.current_timezone(), ts)
    return events.withColumn("at", ts.cast("timestamp"))


def trajectories(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each user's path of a day, once the day is over and the watermark past it; later events are dropped."""
    v = water_vertices(_instants(events).withWatermark("at", late), "at")
    day = v.groupBy("geom_id", F.window("at", "1 day").alias("day")).agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "x", "y"))).alias("v"))
    path = F.transform("v", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y")))
    return day.select("geom_id", F.when(F.size("v") == 1, "POINT").otherwise("LINESTRING").alias("kind"), F.array(path).alias("rings"))


class IndexHolder:
    """A saved index with one writer. Its manifest names each stream's last batch, so a replay after any restart changes nothing."""

    def __init__(self, spark: SparkSession, path: str, stream: str = "events"):
        self.spark, self.path, self.stream = spark, path, stream

    @property
    def index(self) -> ZIndex:
        return storage.load(self.spark, self.path)

    def _apply(self, op: str, batch: DataFrame, batch_id: int, change) -> None:
        rows = settle(batch)  # a stateful stream wants every batch read whole, also one that is in already
        ix, key = self.index, f"{self.stream}:{op}"
        if batch_id > ix.applied.get(key, -1):
            storage.save(replace(change(ix, rows), applied={**ix.applied, key: batch_id}), self.path)

    def insert_batch(self, batch: DataFrame, batch_id: int) -> None:
        """Rows take the place of equal (geom_id, zmin)."""
        self._apply("insert", batch, batch_id, lambda ix, rows: insert(ix, with_zinterval(with_mbr(rows).where("x0 is not null"), ix.config.units_per_cell), upsert=True))

    def delete_batch(self, batch: DataFrame, batch_id: int) -> None:
        """Rows (geom_id, zmin) go."""
        self._apply("delete", batch, batch_id, delete)


def start(stream: DataFrame, holder: IndexHolder, checkpoint: str) -> StreamingQuery:
    """Feeds finished trajectories of an event stream into the holder's index until the source is drained."""
    return trajectories(stream).writeStream.outputMode("append").foreachBatch(holder.insert_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def answers(windows: DataFrame, holder: IndexHolder, rel: str, out: str, checkpoint: str) -> StreamingQuery:
    """Answers a stream of windows from the saved index, each batch from its latest version, into files by batch."""

    def answer(batch: DataFrame, batch_id: int) -> None:
        range_join(holder.index, settle(batch), rel).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return windows.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def ingested(events: DataFrame, bulk: DataFrame, cfg: IndexConfig, replays: int = 0) -> ZIndex:
    """The index of ``bulk`` after a stream of events has been fed into it, then fed again ``replays`` times from the start."""
    spark = bulk.sparkSession
    at = new_path(spark, "stream")
    storage.save(build_index(bulk, cfg), f"{at}/index")
    for n in range(replays + 1):
        start(events, IndexHolder(spark, f"{at}/index"), f"{at}/log{n}").awaitTermination()
    return storage.load(spark, f"{at}/index")


def drained(stream: DataFrame) -> DataFrame:
    """All finished trajectories of a stream, run once into files of the shared folder."""
    spark = stream.sparkSession
    at = new_path(spark, "drained")
    out = trajectories(stream)
    out.writeStream.outputMode("append").format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{at}/out")
