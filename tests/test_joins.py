"""Every method gives the same result, verdicts are sound, and the plans are the ones meant."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rasterruns.functions import geometry, sql
from rasterruns.grid import GridSpec
from rasterruns.operators import approximate, filters, mbr, pairstage, tiles
from rasterruns.operators.refine import refine
from rasterruns.plans import join
from rasterruns.runtime import materialize
from rasterruns.sources import store, wkt
from rasterruns.sources.layers import load_layer, with_mbr
from rasterruns.streaming import tracks

SF01 = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def layers(spark):
    return {n: materialize(load_layer(spark, SF01, n)) for n in ("ponds", "sites", "counties", "tracks")}


def pairs(df):
    rows = [tuple(r) for r in df.select("rid", "sid").collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def verdicts(df):
    return {(r.rid, r.sid): r.verdict for r in df.collect()}


@pytest.mark.parametrize("predicate,r,s", [("intersects", "sites", "ponds"), ("within", "ponds", "sites"), ("line", "counties", "tracks")])
def test_methods_agree_and_are_sound(layers, predicate, r, s):
    a, b = layers[r], layers[s]
    truth = pairs(refine(mbr.mbr_join(a, b), a, b, predicate))
    for m in join.METHODS:
        if predicate == "line" and m in ("coded", "coded_compressed", "local_raster"):
            with pytest.raises(ValueError):
                join.spatial_join(a, b, predicate, m)
            continue
        got = join.spatial_join(a, b, predicate, m, GridSpec(11))
        assert pairs(got.pairs) == truth, m
        v = verdicts(got.verdicts)
        assert all((p in truth) == (x == "hit") for p, x in v.items() if x != "unsure"), m
        assert m != "corner_hull" or "hit" not in v.values()


def test_dual_and_coded(layers):
    a, b = layers["sites"], layers["ponds"]
    got = {m: verdicts(join.spatial_join(a, b, method=m, grid=GridSpec(11)).verdicts) for m in ("dual", "coded", "dual_compressed", "coded_compressed")}
    of = lambda m, x: {p for p, v in got[m].items() if v == x}
    assert of("dual", "miss") == of("coded", "miss") and of("dual", "hit") <= of("coded", "hit") and got["dual"] == got["dual_compressed"] and got["coded"] == got["coded_compressed"]
    swapped = filters.coded_filter(mbr.mbr_join(a, b).drop("tile_id"), *(approximate.build_coded(x, GridSpec(11), "R") for x in (a, b)), same_side=True)
    assert verdicts(swapped) == got["coded"]


def test_orders_nest(layers):
    a, b = layers["sites"], layers["counties"]
    last = None
    for o in (7, 8, 9, 10):
        v = verdicts(join.spatial_join(a, b, grid=GridSpec(o)).verdicts)
        if last:
            assert all(v[p] == x for p, x in last.items() if x != "unsure")
        last = v
    mixed = verdicts(join.spatial_join(a, b, order_left=10, order_right=8).verdicts)
    assert all(last[p] == x for p, x in mixed.items() if x != "unsure")
    for m in filters.ORDERS:
        assert verdicts(join.spatial_join(a, b, grid=GridSpec(10), merge_order=m).verdicts) == last
    with pytest.raises(ValueError):
        join.spatial_join(a, b, merge_order="CC,CC,CK")


def test_tiles(layers):
    a, b = layers["sites"], layers["counties"]
    truth = pairs(join.spatial_join(a, b, grid=GridSpec(10)).pairs)
    for t in (tiles.uniform_tiles(1), tiles.uniform_tiles(3), tiles.quadtree_tiles([a, b], 200)):
        assert pairs(join.partitioned_join(a, b, order=10, tiles=t).pairs) == truth
    with pytest.raises(ValueError):
        tiles.raster_boxes([tiles.replicate(a, tiles.uniform_tiles(2))], 17)
    every = pairs(mbr.mbr_join(a, b, strategy="nested"))
    for s in ("tiled", "sweep", "broadcast"):
        assert pairs(mbr.mbr_join(a, b, strategy=s)) == every


def test_empty_layers(layers):
    a, none = layers["sites"], layers["ponds"].limit(0)
    for m in join.METHODS:
        assert join.spatial_join(a, none, method=m, grid=GridSpec(10)).pairs.count() == 0


def test_rejects(spark):
    rows = [(1, [(5, 5), (9, 5), (9, 9)]), (2, [(5, 5), (9, 9), (9, 5), (5, 9)]), (3, [(5, 5), (6, 6)]), (4, [(0, 5), (9, 5), (9, 9)])]
    df = spark.createDataFrame([(i, [{"x": x, "y": y} for x, y in r]) for i, r in rows], "oid long, ring array<struct<x:bigint,y:bigint>>")
    good, bad = approximate.check_rings(df)
    assert [r.oid for r in good.collect()] == [1] and {r.oid: r.reason for r in bad.collect()} == {2: "not simple", 3: "fewer than three points", 4: "outside the domain"}


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, layers, tmp_path):
    a, b = layers["sites"], layers["ponds"]
    p = plan(mbr.mbr_join(a, b))
    assert "CartesianProduct" not in p and "NestedLoop" not in p and "ring" not in p
    assert "Exchange" not in plan(approximate.build_dual(a, GridSpec(11)))
    assert plan(join.verdicts(mbr.mbr_join(a, b).drop("tile_id"), a, b, grid=GridSpec(11))).count("MapInArrow") == 3
    path = f"file://{tmp_path}/layer"
    store.write_layer(a, path)
    p = plan(mbr.window(store.read_layer(spark, path), (1, 1, 9, 9)).select("oid"))
    assert "LessThanOrEqual(xmin,9)" in p and "ring" not in p
    store.write_dual(approximate.build_dual(a, GridSpec(11)), f"file://{tmp_path}/dual", "sites")
    got = store.read_dual(spark, f"file://{tmp_path}/dual", "sites", 11)
    assert got.count() == a.count() and "PartitionFilters: [isnotnull(layer" in plan(got)


def test_selection_uses_stored_lists(layers):
    a = layers["sites"]
    probes = layers["counties"].limit(10)
    stored = materialize(approximate.build_dual(a, GridSpec(9)))
    assert pairs(join.spatial_select(a, probes, grid=GridSpec(9), stored=stored).pairs) == pairs(join.spatial_select(a, probes, "direct").pairs)
    assert join.choose_order(layers["ponds"]) >= join.choose_order(layers["counties"], 500)


def test_coarsen_frame(layers):
    a = layers["sites"]
    fine = {r.oid: r.cover for r in join.coarsen(approximate.build_dual(a, GridSpec(12)), 10).collect()}
    low = {r.oid: r.cover for r in approximate.build_dual(a, GridSpec(10)).collect()}
    assert fine.keys() == low.keys()
    cells = lambda v: {h for x, y in zip(v[0::2], v[1::2], strict=True) for h in range(x, y)}
    assert all(cells(fine[k]) <= cells(low[k]) for k in low)


def test_sql_surface(spark, layers):
    sql.register(spark)
    layers["sites"].limit(30).createOrReplaceTempView("t_sites")
    layers["counties"].limit(5).createOrReplaceTempView("t_counties")
    d = spark.sql("SELECT oid, list, st, en FROM t_sites, LATERAL dual_runs(ring, 10)")
    assert d.where("list = 'cover'").count() > 0
    got = spark.sql("SELECT a.oid, runs_of(c.hid) AS runs FROM t_sites a, LATERAL edge_cells(a.ring, 10) c GROUP BY a.oid")
    assert got.count() == 30
    approximate.build_dual(layers["sites"].limit(30), GridSpec(9)).createOrReplaceTempView("t_r")
    approximate.build_dual(layers["counties"].limit(5), GridSpec(9)).createOrReplaceTempView("t_s")
    v = spark.sql("SELECT r.oid AS rid, s.oid AS sid, dual_verdict(r.cover, r.core, s.cover, s.core) AS verdict, dual_within_verdict(r.cover, s.cover, s.core) AS w, runs_overlap(r.cover, s.cover) AS o FROM t_r r CROSS JOIN t_s s")
    exact = {(r.rid, r.sid): (r.i, r.w) for r in spark.sql("SELECT r.oid AS rid, s.oid AS sid, polygons_intersect(r.ring, s.ring) AS i, polygon_within(r.ring, s.ring) AS w FROM t_sites r CROSS JOIN t_counties s").collect()}
    for r in v.collect():
        i, w = exact[r.rid, r.sid]
        assert r.verdict == "unsure" or (r.verdict == "hit") == i
        assert r.w == "unsure" or (r.w == "hit") == w
        assert r.o or r.verdict == "miss"
    row = spark.sql("SELECT vbyte_decode(vbyte_encode(array(3L, 9L, 700L, 90000L))) AS v, hilbert_id(3L, 4L, 5) AS h, hilbert_cell(hilbert_id(3L, 4L, 5), 5) AS c, pip(5L, 5L, array(named_struct('x', 1L, 'y', 1L), named_struct('x', 9L, 'y', 1L), named_struct('x', 5L, 'y', 9L))) AS p").first()
    assert row.v == [3, 9, 700, 90000] and (row.c.cx, row.c.cy) == (3, 4) and row.p


def test_wkt_source(spark, layers, tmp_path):
    wkt.register(spark)
    rows = layers["sites"].select("oid", wkt.to_wkt(F.col("ring"), True).alias("wkt"))
    rows.write.format("wktlines").mode("append").save(str(tmp_path / "w"))
    back = spark.read.format("wktlines").load(str(tmp_path / "w")).select("oid", wkt.from_wkt(F.col("wkt")).alias("ring"))
    assert back.join(layers["sites"].select("oid", F.col("ring").alias("old")), "oid").where("ring = old").count() == layers["sites"].count()
    rows.write.option("sep", "\t").csv(str(tmp_path / "c"))
    assert store.read_csv_layer(spark, str(tmp_path / "c")).count() == layers["sites"].count()
    layers["sites"].write.json(str(tmp_path / "j"))
    layers["sites"].write.orc(str(tmp_path / "o"))
    assert store.read_json_layer(spark, str(tmp_path / "j")).count() == store.read_orc_layer(spark, str(tmp_path / "o")).count()


def _drain(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()


def test_wkt_refuses_what_it_cannot_read(spark):
    texts = ["POLYGON ((1 2, 9 2, 9 9, 1 2))", "POLYGON ((1.5 2.5, 9.5 2.5, 9.5 9, 1.5 2.5))", "POLYGON ((0 0, 9 0, 9 9, 0 0), (1 1, 2 1, 2 2, 1 1))", "MULTIPOLYGON (((0 0, 9 0, 9 9, 0 0)))", "POLYGON ((1 2, 9 2, 9 9))", "POLYGON ((1 2 3, 9 2 3, 9 9 3, 1 2 3))", "LINESTRING (1 2, -3 4)", "", None]
    rows = spark.createDataFrame(list(enumerate(texts)), "oid int, wkt string")
    got = {r.oid: r.p and [tuple(x) for x in r.p] for r in rows.select("oid", wkt.from_wkt(F.col("wkt")).alias("p")).collect()}
    assert got == {**{i: None for i in range(9)}, 0: [(1, 2), (9, 2), (9, 9)], 6: [(1, 2), (-3, 4)]}
    assert {r.oid for r in wkt.wkt_rejects(rows).collect()} == {1, 2, 3, 4, 5, 7, 8}


def test_hot_tiles_and_objects_are_dealt(spark, layers, monkeypatch):
    monkeypatch.setattr(mbr, "HOT", 100)
    monkeypatch.setattr(pairstage, "SPLIT", 64)
    here = F.when(F.col("oid") % 10 < 9, F.lit(300000)).otherwise(F.col("xmin"))
    crowd = layers["ponds"].withColumn("dx", here - F.col("xmin")).withColumn("dy", F.when(F.col("dx") != 0, 300000 - F.col("ymin")).otherwise(0))
    crowd = with_mbr(crowd.select("oid", F.transform("ring", lambda p: F.struct((p["x"] + F.col("dx")).alias("x"), (p["y"] + F.col("dy")).alias("y"))).alias("ring")))
    square = [(290000, 290000), (310000, 290000), (310000, 310000), (290000, 310000)]
    one = with_mbr(spark.createDataFrame([(1, square), (2, square)], "oid long, ring array<struct<x:long,y:long>>"))
    for r, s in ((crowd, one), (one, crowd)):
        want = {tuple(x) for x in mbr.mbr_join(r, s, strategy="nested").select("rid", "sid").collect()}
        assert len(want) > 2000
        for strategy in ("tiled", "sweep"):
            got = [tuple(x) for x in mbr.mbr_join(r, s, strategy=strategy).select("rid", "sid").collect()]
            assert len(got) == len(set(got)) and set(got) == want
        found = join.spatial_join(r, s, grid=GridSpec(12))
        assert found.verdicts.count() == len(want)
        assert {(x.rid, x.sid) for x in found.pairs.collect()} == {(x.rid, x.sid) for x in join.spatial_join(r, s, method="direct").pairs.collect()}


def test_streams(spark, layers, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    for i, e in enumerate(events.orderBy("ts").limit(400).repartitionByRange(4, "ts").sortWithinPartitions("ts").toPandas().groupby(lambda k: k // 100)):
        spark.createDataFrame(e[1], events.schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "e"))
    _drain(tracks.stream_segments(stream), "segs")
    got = {r.oid for r in spark.table("segs").collect()}
    assert got == {r.oid for r in tracks.segments(spark.read.parquet(str(tmp_path / "e"))).collect()}
    held = spark.read.parquet(str(tmp_path / "e"))
    far = "3650 days"  # nothing is late: streams give what batches give (append mode keeps open windows back)
    w = F.window(F.col("ts").cast("timestamp"), "1 hour")
    _drain(tracks.windowed_counts(stream, "ts", ["event_type"], "1 hour", late=far), "t_w", "complete")
    assert _bag(spark.table("t_w")) == _bag(held.groupBy(w.alias("window"), "event_type").count())
    _drain(tracks.windowed_counts(stream, "ts", [], "2 hours", "1 hour", far), "t_s", "complete")
    assert _bag(spark.table("t_s")) == _bag(held.groupBy(F.window(F.col("ts").cast("timestamp"), "2 hours", "1 hour").alias("window")).count())
    _drain(tracks.session_counts(stream, "ts", ["user_id"], "6 hours", far), "t_x", "complete")
    assert _bag(spark.table("t_x")) == _bag(held.groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "6 hours").alias("w")).count())
    _drain(tracks.deduplicated(stream, "ts", ["user_id", "event_type"], far), "t_d")
    assert _bag(spark.table("t_d").select("user_id", "event_type")) == _bag(held.select("user_id", "event_type").distinct())
    _drain(tracks.follow_ups(stream, "click", "purchase", "6 hours", far), "t_f")
    a, b = held.where("event_type = 'click'").alias("a"), held.where("event_type = 'purchase'").alias("b")
    both = a.join(b, F.expr("a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOURS"))
    assert _bag(spark.table("t_f").select("first_id", "then_id")) == _bag(both.select("a.event_id", "b.event_id"))


def _bag(df):
    return sorted(str(tuple(r)) for r in df.collect())


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    schema = "ts timestamp, k string"
    path = str(tmp_path / "late")
    (tmp_path / "late").mkdir()
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)
    counts = tracks.windowed_counts(stream, "ts", ["k"], "1 hour", late="1 hour")
    q = None
    for rows in ([("2024-01-01 10:10:00", "a"), ("2024-01-01 10:20:00", "a")], [("2024-01-01 15:00:00", "a")], [("2024-01-01 10:30:00", "a"), ("2024-01-01 14:30:00", "a")], [("2024-01-01 20:00:00", "a")]):
        spark.createDataFrame(rows, "ts string, k string").select(F.col("ts").cast("timestamp").alias("ts"), "k").coalesce(1).write.mode("append").parquet(path)
        q = q or counts.writeStream.format("memory").queryName("late").outputMode("append").start()
        q.processAllAvailable()
    dropped = sum(o.get("numRowsDroppedByWatermark", 0) for p in q.recentProgress for o in p["stateOperators"])
    q.stop()
    got = {r.window.start.hour: r.n for r in spark.table("late").collect()}
    assert got == {10: 2, 14: 1, 15: 1} and dropped == 1


def test_stream_static_selection_equals_the_batch(spark, layers, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    e = events.toPandas().sort_values("ts").head(400)
    for i in range(0, 400, 200):
        spark.createDataFrame(e[i : i + 200], events.schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "e"))
    held = tracks.segments(spark.read.parquet(str(tmp_path / "e")))
    for exact, name in ((False, "v"), (True, "x")):
        q = tracks.select_stream(tracks.stream_segments(stream), layers["counties"], GridSpec(8), str(tmp_path / name), str(tmp_path / f"c{name}"), exact=exact).start()
        q.processAllAvailable()
        q.stop()
        got = {tuple(r) for r in spark.read.parquet(str(tmp_path / name)).drop("batch").collect()}
        if not exact:
            assert got == {tuple(r) for r in tracks.filter_segments(held, layers["counties"], GridSpec(8)).collect()} and got
        else:
            pairs = join.spatial_join(layers["counties"], tracks.as_paths(held), "line", "direct").pairs
            assert got == {(r.rid, r.sid) for r in pairs.collect()} and got


def test_spiky_stars(spark, layers):
    """Irregular shapes: constructions give equal lists, and every method the brute-force join."""
    blobs, sites = materialize(load_layer(spark, SF01, "blobs")), layers["sites"]
    assert blobs.count() == spark.read.parquet(f"{SF01}/embeddings.parquet").count()
    first = [{r.oid: (r.cover, r.core) for r in approximate.build_dual(blobs, GridSpec(10), m).collect()} for m in ("onestep_neighbours", "scanline")]
    assert first[0] == first[1]
    rings = {n: [(r.oid, np.array([(p.x, p.y) for p in r.ring])) for r in x.select("oid", "ring").collect()] for n, x in (("a", blobs), ("b", sites))}
    boxes = [(o, ring, ring.min(0), ring.max(0)) for o, ring in rings["b"]]
    truth = set()
    for o, ring in rings["a"]:
        low, high = ring.min(0), ring.max(0)
        truth |= {(o, p) for p, other, lo, hi in boxes if (low <= hi).all() and (lo <= high).all() and geometry.polygons_intersect(ring, other)}
    assert truth
    for m in ("dual", "coded", "corner_hull"):
        assert pairs(join.spatial_join(blobs, sites, method=m, grid=GridSpec(11)).pairs) == truth, m
