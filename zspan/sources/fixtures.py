"""Geometry sets derived from the given tables: geom_id, kind, rings. Integer units of the default cell."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.geometry.mbr import with_mbr
from zspan.interval import with_zinterval
from zspan.sources.tables import load

SETS = ("roads", "parks", "water")


def _lines(vertices: DataFrame, order: list[str]) -> DataFrame:
    """One line (or point) of each geom_id, through its vertices in order."""
    v = F.sort_array(F.collect_list(F.struct(*order, "x", "y")))
    got = vertices.groupBy("geom_id").agg(v.alias("v"))
    path = F.transform("v", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y")))
    return got.select("geom_id", F.when(F.size("v") == 1, "POINT").otherwise("LINESTRING").alias("kind"), F.array(path).alias("rings"))


def roads(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    n, key = F.col("c_nationkey").cast("long"), F.col("o_orderkey")
    wide = (1 + F.col("o_custkey") % 10) * 1000
    step = F.when(key % 100 == 0, 200).otherwise(1) * 500
    ax = (n % 5) * 144_000_000 + 72_000_000 + ((key * 7919) % 4001 - 2000) * wide
    ay = F.floor(n / 5) * 72_000_000 + 36_000_000 + ((key * 104729) % 4001 - 2000) * wide
    v = li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, o["o_custkey"] == c["c_custkey"])
    v = v.select(key.alias("geom_id"), "l_linenumber", "l_partkey", "l_suppkey", (ax + (F.col("l_partkey") % 200) * step).cast("long").alias("x"), (ay + (F.col("l_suppkey") % 100) * step).cast("long").alias("y"))
    return _lines(v, ["l_linenumber", "l_partkey", "l_suppkey"])


def water(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lines(water_vertices(load(spark, sf_dir, "events")), ["ts", "event_id"])


def water_vertices(events: DataFrame, *keep: str) -> DataFrame:
    """Each event as a vertex of its user's path of the day; also for streams."""
    k = F.from_json("props", "k long")["k"]
    user = F.col("user_id")
    x = ((user * 7919) % 700) * 1_000_000 + F.round(F.col("value") * 100).cast("long") * 100
    y = ((user * 104729) % 350) * 1_000_000 + k * 10_000
    return events.select((user * 100 + F.dayofmonth("ts")).alias("geom_id"), "ts", "event_id", x.alias("x"), y.alias("y"), *keep)


def _ring(x: Column, y: Column, s: Column, corners: tuple[tuple[float, float], ...]) -> Column:
    return F.array(*[F.struct((x + (s * a).cast("long")).alias("x"), (y + (s * b).cast("long")).alias("y")) for a, b in corners])


def parks(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_size")
    key = F.col("p_partkey")
    s = F.col("p_size").cast("long") * 2000 * F.when(key % 100 == 0, 100).otherwise(1)
    x = F.regexp_extract("p_brand", r"(\d+)", 1).cast("long") * 26_000_000 + ((key * 7919) % 4001) * 4000
    y = ((key * 104729) % 4001) * 40_000 + 50_000_000
    ell = _ring(x, y, s, ((0, 0), (2, 0), (2, 1), (1, 1), (1, 2), (0, 2), (0, 0)))
    triangle = _ring(x, y, s, ((0, 0), (2, 0), (0, 2), (0, 0)))
    hole = _ring(x, y, s, ((0.25, 0.25), (0.75, 0.25), (0.75, 0.75), (0.25, 0.75), (0.25, 0.25)))
    shell = F.when(key % 11 == 0, triangle).otherwise(ell)
    return p.select(key.alias("geom_id"), F.lit("POLYGON").alias("kind"), F.when(key % 7 == 0, F.array(shell, hole)).otherwise(F.array(shell)).alias("rings"))


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings' first two components on the map, their label kept."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", "label", F.element_at("embedding", 1).cast("double").alias("a"), F.element_at("embedding", 2).cast("double").alias("b"))
    at = lambda c, half: F.least(F.greatest(F.floor((c + 1) * F.lit(float(half))), F.lit(0)), F.lit(2 * half - 1)).cast("long")
    return e.select(F.col("vec_id").alias("geom_id"), F.lit("POINT").alias("kind"), F.array(F.array(F.struct(at(F.col("a"), 360_000_000).alias("x"), at(F.col("b"), 180_000_000).alias("y")))).alias("rings"), "label")


def nation_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """25 rectangles that cover the domain, as windows with the nation's name and region."""
    n = F.col("n_nationkey").cast("long")
    x, y = (n % 5) * 144_000_000, F.floor(n / 5) * 72_000_000
    return load(spark, sf_dir, "nation").select(n.alias("qid"), "n_name", F.col("n_regionkey").alias("regionkey"), x.alias("wx0"), (x + 144_000_000).alias("wx1"), y.alias("wy0"), (y + 72_000_000).alias("wy1"))


def geometries(spark: SparkSession, sf_dir: str, name: str, units_per_cell: int = 1) -> DataFrame:
    """A set with boxes and intervals; geometries without a vertex drop out."""
    made = {"roads": roads, "parks": parks, "water": water, "points": points}[name](spark, sf_dir)
    return with_zinterval(with_mbr(made).where("x0 is not null"), units_per_cell)
