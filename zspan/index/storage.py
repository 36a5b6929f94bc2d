"""An index as files: stores, directories, staircase, and a manifest that names the version and the batches it holds."""

from __future__ import annotations

import json
import uuid
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from zspan.config import IndexConfig
from zspan.index.build import Store, ZIndex, indexed


def _store(store: Store, path: str, name: str, version: str) -> dict:
    """Segments that the folder lacks are copied; those that an index loaded from it has added lie there already."""
    root = f"{path}/{name}"
    store.leaves.write.parquet(f"{path}/{version}/{name}_leaves")
    if store.root != root:
        for k in store.segments:
            own = store.rows.where(F.col("seg") == k).drop("seg")
            own.sortWithinPartitions("leaf_band", store.key).write.mode("overwrite").partitionBy("leaf_band").parquet(f"{root}/seg={k}")
    return {"root": root, "segments": list(store.segments), "schema": store.schema.jsonValue(), "leaves": f"{path}/{version}/{name}_leaves"}


def save(ix: ZIndex, path: str) -> None:
    """Adds version ``ix.version`` to the folder; the manifest comes last, so readers never see half of one."""
    at, spark = f"v{ix.version}-{uuid.uuid4().hex[:8]}", ix.leaves.sparkSession
    manifest = {"version": ix.version, "threshold": ix.threshold, "config": asdict(ix.config), "applied": ix.applied, "skipped": ix.skipped, "stats": ix.stats, "main": _store(ix.main_store, path, "main", at)}
    if ix.outlier_store is not None:
        manifest["outlier"] = _store(ix.outlier_store, path, "outlier", at)
    for name in ("stairs", "tombstones"):
        if getattr(ix, name) is not None:
            getattr(ix, name).write.parquet(f"{path}/{at}/{name}")
            manifest[name] = f"{path}/{at}/{name}"
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("append").text(f"{path}/manifest")


def manifests(spark: SparkSession, path: str) -> list[dict]:
    """All saved versions; none where nothing was saved."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/manifest")
    if not p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
        return []
    return [json.loads(r["value"]) for r in spark.read.text(f"{path}/manifest").collect()]  # one line a version


def load(spark: SparkSession, path: str, version: int | None = None) -> ZIndex:
    """The latest version, or the one asked for."""
    found = [m for m in manifests(spark, path) if version is None or m["version"] == version]
    m = max(found, key=lambda x: x["version"])
    cfg = IndexConfig(**m["config"])

    def store(name: str) -> Store | None:
        if name not in m:
            return None
        own = m[name]
        return indexed(own["root"], tuple(own["segments"]), T.StructType.fromJson(own["schema"]), spark.read.parquet(own["leaves"]), cfg, spark)

    def table(name: str) -> DataFrame | None:
        return spark.read.parquet(m[name]) if name in m else None

    return ZIndex(cfg, store("main"), store("outlier"), table("stairs"), m["threshold"], table("tombstones"), m["version"], m["skipped"], m["applied"], m["stats"])
