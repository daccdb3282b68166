"""The stage over tiles: the same verdicts as pairs found first, no broadcast of geometry, nothing written a pair."""

import pytest
from pyspark.sql import functions as F

from rasterruns.grid import GridSpec
from rasterruns.operators import boxstage, mbr
from rasterruns.operators.tiles import quadtree_tiles, uniform_tiles
from rasterruns.plans import join
from rasterruns.queries import spatial


def rows(df):
    got = df.select("rid", "sid", "verdict").collect()
    assert len(got) == len({(r.rid, r.sid) for r in got})
    return {tuple(r) for r in got}


@pytest.mark.parametrize("predicate,r,s", [("intersects", "sites", "ponds"), ("within", "ponds", "sites"), ("intersects", "sites", "counties")])
@pytest.mark.parametrize("method", ["dual", "coded_compressed", "local_raster", "corner_hull", "direct"])
def test_same_verdicts_as_pairs_found_first(spark, sf_dir, predicate, r, s, method, monkeypatch):
    monkeypatch.setattr(boxstage, "HELD", 7)
    monkeypatch.setattr(boxstage, "PASSING", 50)
    a, b = (spatial.layer(spark, sf_dir, x) for x in (r, s))
    pairs = mbr.mbr_join(a, b).drop("tile_id")
    want = rows(join.verdicts(pairs, a, b, predicate, method, GridSpec(10)))
    assert want
    for tiles in (uniform_tiles(3), quadtree_tiles([a, b], 40, 3)):
        assert rows(join.box_verdicts(a, b, predicate, method, GridSpec(10), "intersects", tiles)) == want


def test_one_shuffle_and_no_broadcast_of_geometry(spark, sf_dir):
    a, b = (spatial.layer(spark, sf_dir, x) for x in ("sites", "counties"))
    for method in ("local_raster", "corner_hull", "dual"):
        plan = join.box_verdicts(a, b, method=method, grid=GridSpec(8))._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("MapInArrow") == 1
        for line in plan.splitlines():
            assert not ("Join" in line and "cells" in line)
    pairs = mbr.mbr_join(a, b).drop("tile_id")
    plan = join.verdicts(pairs, a, b, method="local_raster")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "cells" in plan
    assert not any("BroadcastExchange" in x and "cells" in x for x in plan.splitlines())


def test_joins_write_no_pairs(spark, sf_dir, monkeypatch):
    a, b = (spatial.layer(spark, sf_dir, x) for x in ("sites", "ponds"))
    from rasterruns.operators import pairstage

    def stop(*_):
        raise AssertionError("pairs are written")

    for module in (join, pairstage):
        monkeypatch.setattr(module, "materialize", stop)
    got = join.spatial_join(a, b, grid=GridSpec(11))
    assert got.pairs.count() and got.verdicts.where(F.col("verdict") == "hit").count()


def test_blocks_of_many_rows_equal_one_cursor_a_row():
    import numpy as np

    from rasterruns.functions import codec
    from rasterruns.operators import filters

    rng = np.random.default_rng(5)
    size = np.array([0, 2, 400, 90, 6, 250])
    sides = []
    for _ in range(2):
        values = np.concatenate([np.sort(rng.choice(200_000, n, replace=False)) for n in size])
        sides.append(codec.encode(values, np.concatenate([[0], np.cumsum(size)])))
    i, j = (x.ravel() for x in np.meshgrid(np.arange(6), np.arange(6)))
    a, b = codec.Cursors(sides[0], i, 20), codec.Cursors(sides[1], j, 20)
    got = filters._blockwise_overlap(a, b, len(i))
    for k in range(len(i)):
        x, y = codec.Cursor(sides[0][int(i[k])].as_py(), 20), codec.Cursor(sides[1][int(j[k])].as_py(), 20)
        assert got[k] == codec.cursors_overlap(x, y)
        assert (a.read[k], b.read[k]) == (x.read, y.read)
    assert got.any() and not got.all()


@pytest.mark.parametrize("method", ["coded", "corner_hull", "local_raster", "direct"])
def test_shares_count_in_the_stage(spark, sf_dir, method):
    """The shares read counts of chunks, not a row a pair, and equal the counts of all verdicts."""
    a, b = (spatial.layer(spark, sf_dir, x) for x in ("sites", "ponds"))
    got = join.spatial_join(a, b, method=method, grid=GridSpec(11))
    want = {x.verdict: x["count"] for x in got.verdicts.groupBy("verdict").count().collect()}
    assert {x.verdict: x.n for x in got.stats().collect()} == want
    assert 0 < got.counts.count() < sum(want.values())
    assert got.counts.columns == ["verdict", "n"]


def test_coded_lists_are_decoded_once_an_object(spark, sf_dir, monkeypatch):
    import numpy as np
    import pyarrow as pa

    from rasterruns.functions import codec
    from rasterruns.operators import approximate, filters

    a, b = (approximate.build_coded(spatial.layer(spark, sf_dir, x), GridSpec(8), side, compressed=True).select("runs", "code").limit(40).toArrow().combine_chunks().to_batches()[0] for x, side in (("sites", "R"), ("counties", "S")))
    i, j = (x.ravel() for x in np.meshgrid(np.arange(a.num_rows), np.arange(b.num_rows)))
    zero = pa.array(np.zeros(len(i), np.int64))
    ids = pa.RecordBatch.from_arrays([zero, pa.array(i), pa.array(j)], names=["tile_id", "rid", "sid"])
    read, decode = [], codec.decode
    monkeypatch.setattr(codec, "decode", lambda column: (read.append(len(column)), decode(column))[1])
    kernel = filters.coded_kernel()
    halves = [kernel(ids.slice(x, len(i) // 2), a, i[x:][: len(i) // 2], b, j[x:][: len(i) // 2]).column("verdict").to_pylist() for x in (0, len(i) // 2)]
    assert sum(read) == a.num_rows + b.num_rows
    plain = pa.RecordBatch.from_arrays([*ids.columns, *(c.take(pa.array(i)) for c in a.columns)], names=[*ids.schema.names, "p_runs", "p_code"])
    assert halves[0] + halves[1] == filters._of_pairs(filters.coded_kernel())(plain, b.rename_columns(["q_runs", "q_code"]), j).column("verdict").to_pylist()
    assert {"miss", "unsure"} <= {*halves[0], *halves[1]}
