"""The experiment queries cover all layers, pairs and tilings that the survey lists."""

import pytest

from rasterruns.operators import approximate, measures, tiles
from rasterruns.plans import join
from rasterruns.queries import workloads

PAIRS = {"sites-ponds", "sites-counties", *(f"lakes-parks-{g}" for g in range(5))}


class Stop(Exception):
    pass


def labels(spark, monkeypatch, query, owner, name, stub, sf_dir):
    """What a query asks of one function, which is replaced by ``stub``."""
    seen = []
    monkeypatch.setattr(owner, name, lambda *a, **k: (seen.append((a, k)), stub)[1])
    workloads.Q[query](spark, sf_dir)
    return seen


def test_space_covers_all_layers(spark, sf_dir, monkeypatch):
    seen = []

    def report(layers, *_):
        seen.append(set(layers))
        raise Stop

    monkeypatch.setattr(measures, "space_report", report)
    for query in [f"w1_space_{x}" for x in workloads.POLYGONS] + ["w10_space_ratios"]:
        with pytest.raises(Stop):
            workloads.Q[query](spark, sf_dir)
    assert seen == [{x} for x in workloads.POLYGONS] + [set(workloads.POLYGONS)]


def test_regions_take_one_to_four_tiles(spark, sf_dir, monkeypatch):
    class Got:
        verdicts = spark.createDataFrame([], "verdict string, merges long")

    seen = labels(spark, monkeypatch, "w5_tiles_regions", join, "partitioned_join", Got, sf_dir)
    assert sorted(a[2] for a, _ in seen) == sorted([1, 2, 3, 4] * workloads.REGIONS)


def test_constructions_agree_on_all_layers(spark, sf_dir):
    ends = {}
    for r in workloads.Q["w8_constructions"](spark, sf_dir).collect():
        ends.setdefault(r.layer, []).append((r.cover_ends, r.core_ends))
    assert set(ends) == set(workloads.POLYGONS)
    assert all(len(x) == 6 and len(set(x)) == 1 for x in ends.values())


def test_tile_space_covers_all_layers(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(tiles, "raster_boxes", lambda *_: None)
    monkeypatch.setattr(tiles, "assign", lambda x, *_: x)
    empty = spark.createDataFrame([], "cover array<long>, core array<long>")
    monkeypatch.setattr(approximate, "build_dual", lambda *_: empty)
    got = {(r.layer, r.tiles) for x in workloads.POLYGONS for r in workloads.Q[f"w6_tile_space_{x}"](spark, sf_dir).collect()}
    assert got == {(x, p) for x in workloads.POLYGONS for p in (1, 2, 3, 4)}


def test_compression_runs_on_all_pairs(spark, sf_dir):
    n = {}
    for r in workloads.Q["w15_compression"](spark, sf_dir).collect():
        n.setdefault(r.pair, {}).setdefault(r.decoding, {})[r.verdict] = (r.n, r.bytes)
    assert set(n) <= PAIRS and len(n) > 2
    for x in n.values():
        assert {k: v[0] for k, v in x["whole"].items()} == {k: v[0] for k, v in x["plain"].items()}
        assert all(x["whole"][k][1] < x["plain"][k][1] for k in x["whole"])
    assert all(r.reads_less for r in workloads.Q["w15_incremental"](spark, sf_dir).collect())


def test_examples_read_the_sites(spark, sf_dir):
    from rasterruns.grid import GridSpec
    from rasterruns.queries.spatial import FINE, layer

    rows = workloads.Q["w16_examples"](spark, sf_dir).collect()
    cells = approximate.coverage_cells(layer(spark, sf_dir, "sites"), GridSpec(FINE)).count()
    assert sum(r.n for r in rows) == cells > 0
    assert all(r.swaps for r in rows) and {r.code: r.shares_bit for r in rows} == {0b100: False, 0b101: True, 0b011: True}


def test_worked_examples_of_packing_and_alignment():
    import numpy as np

    from rasterruns.operators import filters

    data, _ = approximate.pack_codes(np.array([1, 2, 1]), np.zeros(3, np.int64), np.array([3]), "R")
    assert "".join(map(str, np.unpackbits(data)[:9].tolist())) == "100101100"
    pack = lambda bits: int(bits.ljust(16, "0"), 2).to_bytes(2, "big")
    assert not filters.aligned_and(pack("100101101101"), pack("100100101100"), 6, 6, swap=True)
