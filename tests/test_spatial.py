import os
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from zspan import queries as q
from zspan import sqlapi
from zspan.augment import staircase
from zspan.base import linear, protocol
from zspan.base.search import bisect, gallop
from zspan.baselines import trees
from zspan.config import IndexConfig, QueryOptions
from zspan.curve import zorder
from zspan.geometry import predicates, text, wkb
from zspan.geometry.mbr import with_mbr
from zspan.geometry.model import GEOMETRY
from zspan.index import maintain, storage
from zspan.index.build import BASES, Store, build_index, sort_by_zmin
from zspan.index.query import disjoint, explain_query, late_range_join, locate, plan_leaves, planned, range_join, range_query
from zspan.interval import with_zinterval
from zspan.plans import planned_bytes, settle, small, with_rank
from zspan.sources import textfiles
from zspan.workloads import hybrid
from zspan.workloads.windows import is_bulk

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", ["contains_roads_1pct", "intersects_parks_01pct", "intersects_water_01pct_rtree", "intersects_parks_01pct_quadtree", "contains_parks_01pct_joins", "intersects_parks_01pct_spline", "op_touches_boxes_parks", "index_size_parks", "checked_intersects_parks_1pct", "leafskip_contains_water_01pct", "staircase_parks_m10", "after_insert_intersects_parks", "after_insert_intersects_parks_rtree", "after_delete_compact_intersects_water", "stream_insert_water", "example_stairs", "example_stairs_append"])
def test_query_equals_sql(spark, duck, name):
    df = q.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    want = duck.sql(q.ORACLE_SQL[name])
    at = [want.columns.index(c) for c in cols]
    assert sorted(map(tuple, df.select(cols).collect()), key=str) == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=str)


def _geoms(spark, rows):
    shaped = [(i, kind, [[{"x": x, "y": y} for x, y in ring] for ring in rings]) for i, kind, rings in rows]
    return with_zinterval(with_mbr(spark.createDataFrame(shaped, GEOMETRY)).where("x0 is not null"))


EDGE = [
    (1, "POINT", [[(5, 5)]]),
    (2, "POINT", [[(0, 5)]]),  # on the window's border
    (3, "LINESTRING", [[(0, 0), (0, 10)]]),  # along the border
    (4, "LINESTRING", [[(10, 10), (20, 20)]]),  # touches a corner
    (5, "POLYGON", [[(-0, 0), (100, 0), (100, 100), (0, 100), (0, 0)]]),  # around the window
    (6, "POLYGON", [[(0, 0), (100, 0), (100, 100), (0, 100), (0, 0)], [(0, 0), (50, 0), (50, 50), (0, 50), (0, 0)]]),
    (7, "POLYGON", [[(0, 0), (100, 0), (100, 100), (0, 100), (0, 0)], [(60, 60), (90, 60), (90, 90), (60, 90), (60, 60)]]),
    (8, "LINESTRING", [[(2, 2), (8, 8)]]),
    (9, "LINESTRING", [[(11, 0), (11, 10)]]),
    (10, "LINESTRING", [[(2, 2), (8, 8)]]),
]


def test_edge_shapes(spark):
    g = _geoms(spark, EDGE)
    w = spark.createDataFrame([(0, 0, 10, 0, 10), (1, 5, 5, 5, 5), (2, 70, 80, 70, 80), (3, 200, 300, 200, 300)], "qid long, wx0 long, wx1 long, wy0 long, wy1 long")
    got = {rel: {k: set() for k in range(4)} for rel in ("contains", "intersects")}
    for rel in got:
        for base in ("adaptive_linear", "btree"):
            ix = build_index(g, IndexConfig(base=base, leaf_cap=2, m=2))
            rows = range_join(ix, w, rel).collect()
            assert len(rows) == len(set(rows))
            assert set(rows) == set(trees.scan(g, w, rel).collect())
        for qid, gid in rows:
            got[rel][qid].add(gid)
    assert got["contains"][0] == {1, 8, 10} and got["contains"][1] == set()
    assert got["intersects"][0] >= {1, 2, 3, 4, 5, 7, 8, 10} and 9 not in got["intersects"][0]
    assert got["intersects"][2] == {5, 6} and got["intersects"][3] == set()


def test_general_windows_agree_with_rectangles():
    r = random.Random(4)
    for _ in range(300):
        x0, y0 = r.randint(0, 6), r.randint(0, 6)
        x1, y1 = x0 + r.randint(1, 6), y0 + r.randint(1, 6)
        win = [[{"x": a, "y": b} for a, b in ((x0, y0), (x1, y0), (x1, y1), (x0, y1), (x0, y0))]]
        line = [[{"x": r.randint(0, 12), "y": r.randint(0, 12)} for _ in range(r.randint(1, 4))]]
        kind = "POINT" if len(line[0]) == 1 else "LINESTRING"
        inside = all(x0 <= p["x"] <= x1 and y0 <= p["y"] <= y1 for p in line[0])
        if predicates.relation("contains", "POLYGON", win, kind, line):
            assert inside and predicates.relation("intersects", "POLYGON", win, kind, line)
        assert predicates.relation("disjoint", "POLYGON", win, kind, line) != predicates.relation("intersects", "POLYGON", win, kind, line)
        if predicates.relation("touches", "POLYGON", win, kind, line):
            assert not predicates.relation("contains", "POLYGON", win, kind, line)
    ring = lambda *p: [{"x": a, "y": b} for a, b in p]
    ell = [ring((0, 0), (4, 0), (4, 2), (2, 2), (2, 4), (0, 4), (0, 0))]
    assert not predicates.relation("contains", "POLYGON", ell, "POINT", [ring((3, 3))])
    assert predicates.relation("contains", "POLYGON", ell, "LINESTRING", [ring((0, 0), (3, 1))])
    assert predicates.relation("touches", "POLYGON", ell, "POLYGON", [ring((4, 0), (6, 0), (6, 2), (4, 2), (4, 0))])


def test_codes(spark):
    row = spark.range(1).select(*[zorder.z_address(F.lit(x).cast("long"), F.lit(y).cast("long")).alias(f"c{x}{y}") for x, y in ((0, 1), (1, 3))]).first()
    assert (row["c01"], row["c13"]) == (2, 11)
    big = spark.range(1).select(zorder.z_address_wide(F.lit(2**33).cast("long"), F.lit(5).cast("long")).alias("w")).first()["w"]
    assert int(big) == 2**66 + 0b100010
    with pytest.raises(ValueError):
        zorder.check_bits(1e-8)
    sqlapi.register(spark)
    assert spark.sql("SELECT z_address(1L, 3L) AS z").first()["z"] == 11
    assert [tuple(r) for r in spark.sql("SELECT * FROM z_ranges(0, 1, 1, 3, 16)").collect()] == [(2, 3), (8, 11)]


def test_staircase_is_a_lower_bound(spark):
    r = random.Random(2)
    rows = [(i, a, a + r.randint(0, 40)) for i, a in enumerate(r.randint(0, 300) for _ in range(60))]
    df = with_rank(sort_by_zmin(spark.createDataFrame(rows, "geom_id long, zmin long, zmax long"))).withColumn("leaf_id", F.lit(0))
    new = [(a, a + r.randint(0, 60)) for a in (r.randint(0, 330) for _ in range(15))]
    for m in (1, 4, 16, None):
        stairs = staircase.build(df, m)
        for pieces, have in ((stairs.orderBy("hi_incl").collect(), rows), (staircase.apply_inserts(stairs, spark.createDataFrame(new, "zmin long, zmax long")).orderBy("hi_incl").collect(), rows + [(0, *x) for x in new])):
            table = [(p["hi_incl"], p["start_key"]) for p in pieces]
            assert all(a < b for (a, _), (b, _) in zip(table, table[1:], strict=False)) and [s for _, s in table] == sorted(s for _, s in table)
            for z in range(0, 420, 3):
                reach = [lo for _, lo, hi in have if hi >= z]
                if reach:
                    assert staircase.lookup(table, z) <= min(z, min(reach))
                    if m == 1 and have is rows:
                        assert staircase.lookup(table, z) == min(z, min(reach))


def test_searches_in_sorted_runs():
    r = np.random.default_rng(0)
    for _ in range(100):
        n = r.integers(1, 200)
        keys, q = np.sort(r.integers(0, 100, n)), r.integers(-5, 110, 50)
        lo, hi = np.zeros(50, np.int64), np.full(50, n)
        want = np.maximum(np.searchsorted(keys, q, side="right") - 1, 0)
        assert (bisect(keys, q, lo, hi)[0] == want).all() and (gallop(keys, q, lo, hi, r.integers(-3, n + 3, 50))[0] == want).all()


@pytest.mark.parametrize("base", list(BASES))
def test_bases_locate_alike_on_the_driver_and_by_joins(spark, base):
    r = np.random.default_rng(1)
    for keys in (np.sort((r.random(700) ** 3 * 1e15).astype(np.int64)), np.sort(r.integers(0, 60, 300)), np.array([5])):
        q = np.unique(np.concatenate([keys, keys + 1, keys - 1, [0, 1 << 60]]))
        want = np.maximum(np.searchsorted(keys, q, side="right") - 1, 0)
        leaves = spark.createDataFrame([(i, int(k)) for i, k in enumerate(keys)], "pos long, first_key long")
        b = BASES[base].fit(leaves, keys, fanout=8, max_err=4, radix_bits=6)
        got, steps = b.locate(q)
        assert (got == want).all() and steps.max() < 60
        by_joins = b.probe(spark.createDataFrame([(int(k),) for k in q], "k long"), "k", "at").collect()
        assert {x["k"]: x["at"] for x in by_joins} == dict(zip(q.tolist(), want.tolist(), strict=True))


def test_leaf_models_and_order(spark):
    ix = q.index(spark, SF, "parks")
    first = ix.main.groupBy("leaf_id", "zmin").agg(F.min("rank").alias("rank")).join(ix.leaf_models, "leaf_id").join(ix.leaves.select("leaf_id", "first_rank", "first_key", "n"), "leaf_id")
    assert first.where(F.abs(linear.predicted_slot(F.col("zmin")) - (F.col("rank") - F.col("first_rank"))) > F.col("max_err")).count() == 0
    keys = ix.main.select(F.col("geom_id").alias("qid"), F.col("zmin").alias("key"))
    found = locate(ix, keys).join(ix.main.select(F.col("geom_id").alias("qid"), "zmin", "leaf_id"), "qid")
    assert found.count() == ix.main.count()
    with pytest.raises(protocol.IndexNotOrderPreserving):
        protocol.require_order(linear.two_stage(q.geoms(spark, SF, "roads")))
    with pytest.raises(protocol.IndexNotOrderPreserving):
        build_index(q.geoms(spark, SF, "parks"), IndexConfig(base="two_stage"))
    with pytest.raises(ValueError):
        build_index(q.geoms(spark, SF, "parks"), IndexConfig(sort_key="zmax"))


def test_search_opens_only_the_bands_and_keys_it_needs(spark, monkeypatch):
    monkeypatch.setattr("zspan.index.build.BAND_ROWS", 1)
    monkeypatch.setattr("zspan.index.build.BAND_LEAVES", 4)
    g = q.geoms(spark, SF, "parks")
    ix = build_index(g, IndexConfig(leaf_cap=8, fill=1.0, m=10))
    row = g.orderBy("zmin").first()
    w = spark.createDataFrame([(0, row["x0"], row["x1"], row["y0"], row["y1"])], "qid long, wx0 long, wx1 long, wy0 long, wy1 long")
    for options in (QueryOptions(), QueryOptions(resident=False)):
        plan = range_join(ix, w, "contains", options)._jdf.queryExecution().toString()
        assert "PartitionFilters: [leaf_band" in plan and "GreaterThanOrEqual(zmin," in plan and "LessThanOrEqual(zmin," in plan
        _, rows, _ = planned(ix, w, "contains", options)[0]
        assert 0 < rows.select(F.input_file_name()).distinct().count() < len(ix.main.inputFiles()) / 2
    assert set(range_join(ix, w, "intersects").collect()) == set(range_join(ix, w, "intersects", QueryOptions(resident=False)).collect()) == set(late_range_join(ix, w).collect()) == set(trees.scan(g, w, "intersects").collect())


def test_broadcast_hints_follow_the_size_of_the_table(spark):
    t = settle(spark.range(1000))
    assert planned_bytes(t) < 1 << 20 and "ResolvedHint" in small(t)._jdf.queryExecution().analyzed().toString()
    assert "ResolvedHint" not in small(t, 10)._jdf.queryExecution().analyzed().toString()


def test_maintenance(spark, tmp_path):
    g = _geoms(spark, EDGE)
    w = spark.createDataFrame([(0, 0, 10, 0, 10)], "qid long, wx0 long, wx1 long, wy0 long, wy1 long")
    cfg = IndexConfig(leaf_cap=2, m=2)
    ix = maintain.insert(build_index(g.where("geom_id <= 4"), cfg), g.where("geom_id > 4"))
    assert set(range_join(ix, w, "intersects").collect()) == set(trees.scan(g, w, "intersects").collect())
    gone = maintain.delete(ix, g.where("geom_id = 8"))  # 10 has the same code and stays
    ids = {r["geom_id"] for r in range_join(gone, w, "contains").collect()}
    assert 10 in ids and 8 not in ids
    tidy = maintain.merge_leaves(maintain.compact(gone, 1), 0.9)
    assert {r["geom_id"] for r in range_join(tidy, w, "contains").collect()} == ids
    back = maintain.insert(gone, g.where("geom_id = 8"))
    assert 8 in {r["geom_id"] for r in range_join(back, w, "contains").collect()}
    path = str(tmp_path / "ix")
    storage.save(tidy, path)
    again = storage.load(spark, path)
    assert {r["geom_id"] for r in range_join(again, w, "contains").collect()} == ids
    one = {r["geom_id"] for r in range_query(ix, (0, 10, 0, 10), "intersects").collect()}
    assert one == {r["geom_id"] for r in range_join(ix, w, "intersects").collect()}
    assert explain_query(ix, (0, 10, 0, 10), "intersects").count() == 2
    assert range_join(ix, w, "contains", QueryOptions(refine=False)).count() >= len(ids)
    assert {r["geom_id"] for r in disjoint(g, ix, (0, 10, 0, 10)).collect()} == {r["geom_id"] for r in g.collect()} - one
    twice = maintain.insert(maintain.insert(ix, g.where("geom_id = 8"), upsert=True), g.where("geom_id <= 4"), upsert=True)
    assert sorted(maintain.visible(twice).select("geom_id").collect()) == sorted(g.select("geom_id").collect())
    fresh = maintain.maybe_rebuild(maintain.maybe_rebuild(ix, 2.0), 9.0)
    assert set(range_join(fresh, w, "intersects").collect()) == set(range_join(ix, w, "intersects").collect())


def test_repeated_compaction_and_branches(spark):
    g = q.geoms(spark, SF, "parks")
    w = q.windows(spark, SF, "parks", "1pct")
    want = set(trees.scan(g, w, "intersects").collect())
    base = build_index(g.where("geom_id % 2 = 0"), IndexConfig(leaf_cap=64, m=10))
    half = maintain.insert(base, g.where("geom_id % 4 = 1"))
    other = maintain.insert(base, g.where("geom_id % 4 = 3"))  # another branch of the same version
    ix = maintain.insert(half, g.where("geom_id % 4 = 3"))
    for cap in (32, 16, 8, 4, 3):
        ix = maintain.compact(ix, cap)
        assert ix.leaves.agg(F.max("n")).first()[0] <= cap
    assert set(range_join(ix, w, "intersects").collect()) == want
    assert {r["geom_id"] % 4 for r in maintain.visible(other).select("geom_id").collect()} == {0, 2, 3}


def test_resident_and_joined_upkeep_agree(spark, monkeypatch):
    g, w = q.geoms(spark, SF, "parks"), q.windows(spark, SF, "parks", "1pct")
    want = set(trees.scan(g, w, "intersects").collect())
    monkeypatch.setattr("zspan.index.maintain.BATCH_ROWS", 3)
    ix = maintain.insert(build_index(g.where("geom_id % 3 > 0"), IndexConfig(leaf_cap=16, m=10)), g.where("geom_id % 3 = 0"))
    assert set(range_join(ix, w, "intersects").collect()) == want
    monkeypatch.setattr("zspan.index.build.resident", lambda leaves, bound=0: None)
    ix = maintain.insert(build_index(g.where("geom_id % 3 > 0"), IndexConfig(leaf_cap=16, m=10, base="spline_radix")), g.where("geom_id % 3 = 0"))
    assert isinstance(ix.main_store, Store) and ix.main_store.directory is None
    assert set(range_join(maintain.compact(ix), w, "intersects").collect()) == want


def test_stream_replay_changes_nothing(spark, tmp_path):
    from zspan.streaming.ingest import IndexHolder

    g = q.geoms(spark, SF, "water")
    path = str(tmp_path / "ix")
    storage.save(build_index(g.where("geom_id % 5 > 0"), IndexConfig(leaf_cap=16, m=10)), path)
    late = g.where("geom_id % 5 = 0").select("geom_id", "kind", "rings")
    for _ in range(2):  # the second holder knows nothing of the first
        IndexHolder(spark, path).insert_batch(late, 0)
    assert storage.load(spark, path).version == 1
    IndexHolder(spark, path, "other").insert_batch(late, 0)  # another stream with the same rows: they take their own place
    assert sorted(maintain.visible(storage.load(spark, path)).select("geom_id").collect()) == sorted(g.select("geom_id").collect())


def test_rivals_keep_up(spark):
    g, w = q.geoms(spark, SF, "parks"), q.windows(spark, SF, "parks", "1pct")
    want = set(trees.scan(g, w, "intersects").collect())
    kept = {r["geom_id"] for r in g.where(hybrid.is_bulk()).select("geom_id").collect()}
    for method in ("rtree", "quadtree"):
        got, log = hybrid.after_inserts(g, IndexConfig(), 3, method)
        assert set(got.search(w, "intersects").collect()) == want and len(log) == 3
        gone, _ = hybrid.after_deletes(g, IndexConfig(), 2, method)
        assert set(gone.search(w, "intersects").collect()) == {r for r in want if r["geom_id"] in kept}
    assert hybrid.throughput([hybrid.Done("insert", 0, 1, 5, 9.0), hybrid.Done("insert", 1, 1, 10, 2.0)], "insert") == 5.0


def test_quadtree_beyond_the_drivers_bound(spark, monkeypatch):
    """Quadrants in a table answer as those on the driver do, from the build on and once inserts pass the bound."""
    g, w = q.geoms(spark, SF, "parks"), q.windows(spark, SF, "parks", "1pct")
    bulk, late = g.where(is_bulk()), g.where(~is_bulk())
    plain = trees.Quadtree.fit(g)
    want = {(rel, tuple(r)) for rel in ("contains", "intersects") for r in plain.search(w, rel).collect()}
    checked, size = plain.candidates(w).count(), plain.size_bytes()
    for most in (3, trees.Quadtree.fit(bulk).quads.shape[1]):
        monkeypatch.setattr(trees, "RESIDENT_LEAVES", most)
        grown = trees.Quadtree.fit(bulk).insert(late)
        assert grown.quads is None and grown.size_bytes() == size and grown.candidates(w).count() == checked
        assert {(rel, tuple(r)) for rel in ("contains", "intersects") for r in grown.search(w, rel).collect()} == want
        left = grown.delete(late).search(w, "contains").collect()
        assert {tuple(r) for r in left} == {tuple(r) for r in plain.delete(late).search(w, "contains").collect()}


def test_sql_search_tests_shapes_only_where_boxes_leave_it_open(spark, tmp_path, monkeypatch):
    from zspan.index import reader

    rows = [(i, "POLYGON", [[(x, 10), (x + 4, 10), (x, 14), (x, 10)]]) for i, x in enumerate(range(0, 200, 5))]
    rows += [(100, "LINESTRING", [[(0, 12), (0, 20)]]), (101, "LINESTRING", [[(0, 12), (6, 20)]]), (102, "POINT", [[(3, 3)]]), (103, "POINT", [[(0, 3)]])]
    made = _geoms(spark, rows)
    storage.save(build_index(made, IndexConfig(leaf_cap=8, m=4)), f"file://{tmp_path}/ix")
    window, asked = (0, 150, 0, 30), []
    monkeypatch.setattr(reader, "relation", lambda *a: asked.append(a) or predicates.relation(*a))
    got = sorted(r[0] for r in reader.search(f"file://{tmp_path}/ix", window, "contains"))
    ring = [[{"x": x, "y": y} for x, y in ((0, 0), (150, 0), (150, 30), (0, 30), (0, 0))]]
    assert got == [r["geom_id"] for r in made.orderBy("geom_id").collect() if predicates.relation("contains", "POLYGON", ring, r["kind"], r["rings"])]
    assert len(asked) == 3 and {100, 103}.isdisjoint(got) and {101, 102} <= set(got)


def test_touches_query_leaves_out_corners_on_slanted_edges(spark, tmp_path):
    """The slanted edge of triangle 11 meets nothing of another park's strip but its lower left corner."""
    place = lambda k: (k * 7919 % 4001, k * 104729 % 4001)
    (a, b), other = place(11), next(k for k in range(1, 99) if k % 11 and place(k)[0] > place(11)[0] + 1 and place(k)[1] > place(11)[1])
    size = place(other)[0] - a - 1 + 10 * (place(other)[1] - b)
    parts = [(k, "Brand#11", size if k == 11 else 10) for k in range(1, 99)]
    spark.createDataFrame(parts, "p_partkey long, p_brand string, p_size int").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    c = duckdb.connect()
    c.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet/*.parquet'")
    got = sorted(tuple(r) for r in q.QUERIES["op_touches_boxes_parks"](spark, str(tmp_path)).collect())
    assert got == sorted(c.execute(q.ORACLE_SQL["op_touches_boxes_parks"]).fetchall()) and (other, 11) not in got and got


@pytest.mark.parametrize("name", ["example_lowest", "example_stairs_insert", "example_stairs_append"])
def test_examples_read_the_given_parks(spark, duck, name):
    assert "FROM part)" in q.ORACLE_SQL[name]
    got = q.QUERIES[name](spark, SF)
    assert got.inputFiles() or name != "example_lowest"
    assert sorted(tuple(r) for r in got.collect()) == sorted(duck.execute(q.ORACLE_SQL[name]).fetchall())


def test_shipped_package_stays(spark, monkeypatch, tmp_path):
    import __spark_entry__ as e

    monkeypatch.chdir(tmp_path)
    monkeypatch.setenv("PYTHONPATH", "")
    sent = []
    monkeypatch.setattr(type(spark.sparkContext), "addPyFile", lambda self, path: sent.append(path))
    e._ship(spark)
    assert sent and os.path.exists(sent[0])
    e._SHIPPED.clear()


def test_text_and_binary(spark):
    g = _geoms(spark, EDGE)
    round_trip = text.from_wkt(g.select("geom_id", text.to_wkt(F.col("kind"), F.col("rings")).alias("t")), "t").select("geom_id", "kind", "rings")
    assert sorted(round_trip.collect()) == sorted(g.select("geom_id", "kind", "rings").collect())
    binary = wkb.read(wkb.write(g).select("geom_id", "wkb"), "wkb").select("geom_id", "kind", "rings")
    assert sorted(binary.collect()) == sorted(g.select("geom_id", "kind", "rings").collect())


def test_geojson_and_csv(spark, tmp_path):
    g = _geoms(spark, EDGE)
    json = g.select("geom_id", text.to_geojson(F.col("kind"), F.col("rings")).alias("t"))
    assert sorted(text.from_geojson(json, "t").select("geom_id", "kind", "rings").collect()) == sorted(g.select("geom_id", "kind", "rings").collect())
    features = json.select(F.concat(F.lit('{"type":"Feature","id":'), F.col("geom_id"), F.lit(',"properties":{},"geometry":'), F.col("t"), F.lit("}")).alias("value"))
    odd = spark.createDataFrame([("",), ("{",), ('{"type":"Feature","id":1,"geometry":null}',), ('{"type":"Point","coordinates":[]}',), ('{"type":"Other","coordinates":[1,2]}',)], "value string")
    features.union(odd).write.text(str(tmp_path / "json"))
    assert sorted(textfiles.geojson_lines(spark, str(tmp_path / "json"), cell=None).collect()) == sorted(g.select("geom_id", "kind", "rings").collect())
    several = spark.createDataFrame([('{"type":"MultiPolygon","coordinates":[[[[0,0],[0.5,0],[0,0.5],[0,0]]],[[[1,1],[2,1],[1,2],[1,1]]]]}',)], "t string")
    got = text.from_geojson(several, "t", cell=0.5).first()
    assert got["kind"] == "MULTIPOLYGON" and [len(r) for r in got["rings"]] == [4, 4] and tuple(got["rings"][0][1]) == (361, 180)
    points = spark.createDataFrame([(1, -180.0, -90.0), (2, 0.0, 0.0), (3, None, 1.0)], "geom_id long, lon double, lat double")
    points.write.csv(str(tmp_path / "points"), header=True)
    assert sorted((r["geom_id"], *r["rings"][0][0]) for r in textfiles.csv_points(spark, str(tmp_path / "points")).collect()) == [(1, 0, 0), (2, 360_000_000, 180_000_000)]
    g.select("geom_id", text.to_wkt(F.col("kind"), F.col("rings")).alias("wkt")).write.csv(str(tmp_path / "wkt"), header=True)
    assert sorted(textfiles.csv_wkt(spark, str(tmp_path / "wkt")).collect()) == sorted(g.select("geom_id", "kind", "rings").collect())


def test_plan_prunes_columns(spark):
    plan = q.load(spark, SF, "orders").select("o_orderkey").where("o_orderkey > 5")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(o_orderkey), GreaterThan(o_orderkey,5)]" in plan and "ReadSchema: struct<o_orderkey:bigint>" in plan


def test_data_source_reads_only_keys_in_range(spark, tmp_path):
    from zspan.sources import datasource

    path = str(tmp_path / "ix")
    ix = q.index(spark, SF, "parks")
    storage.save(ix, path)
    datasource.register(spark)
    mid = sorted(r["zmin"] for r in ix.main.select("zmin").collect())[100]
    got = spark.read.format("zspan").option("path", path).option("zlo", mid).load()
    assert {r["geom_id"] for r in got.select("geom_id").collect()} == {r["geom_id"] for r in ix.main.where(F.col("zmin") >= mid).select("geom_id").collect()}
    assert datasource.ZspanReader({"path": path, "zlo": str(1 << 62)}, datasource.SCHEMA).partitions() == []


def test_table_functions_search_a_saved_index(spark, tmp_path):
    path, r = str(tmp_path / "ix"), random.Random(8)
    line = lambda: [(r.randint(0, 400), r.randint(0, 400)) for _ in range(r.randint(1, 4))]
    shapes = [*EDGE, *((100 + i, "POINT" if len(p) == 1 else "LINESTRING", [p]) for i, p in enumerate(line() for _ in range(200)))]
    ix = build_index(_geoms(spark, shapes), IndexConfig(leaf_cap=8, m=4))
    storage.save(ix, path)
    sqlapi.register(spark)
    ask = lambda f, w, rel: spark.sql(f"SELECT * FROM {f}('{path}', {', '.join(map(str, w))}, '{rel}')")
    windows = [(0, 10, 0, 10), (5, 5, 5, 5), (70, 80, 70, 80), (50, 300, 20, 350), (900, 999, 900, 999)]
    for rel in ("contains", "intersects"):
        for w in windows:
            assert sorted(x["geom_id"] for x in ask("zspan_search", w, rel).collect()) == sorted(x["geom_id"] for x in range_query(ix, w, rel).collect()), (rel, w)
            for name in ("main", "outlier"):
                p, got = plan_leaves(ix, w, rel, name), [x for x in ask("zspan_plan", w, rel).collect() if x["store"] == name]
                assert tuple(sorted(x["leaf_id"] for x in got)) == p.leaf_ids and {(x["zstart"], x["zhi"]) for x in got} <= {(p.zstart, p.zhi)}
    ix = maintain.delete(maintain.insert(ix, _geoms(spark, [(900, "POINT", [[(60, 60)]]), (901, "LINESTRING", [[(0, 0), (390, 390)]])])), _geoms(spark, [(900, "POINT", [[(60, 60)]]), shapes[20]]))
    storage.save(ix, path)
    wins = spark.createDataFrame([(i, *w) for i, w in enumerate(windows)], "qid long, wx0 long, wx1 long, wy0 long, wy1 long")
    wins.createOrReplaceTempView("asked")
    for rel in ("contains", "intersects"):
        got = spark.sql(f"SELECT qid, geom_id FROM asked, LATERAL zspan_search('{path}', wx0, wx1, wy0, wy1, '{rel}')")
        assert sorted(got.collect()) == sorted(range_join(ix, wins, rel).collect())
    with pytest.raises(Exception, match="not within"):
        ask("zspan_plan", windows[0], "within").collect()
