"""Local rasters by window: the types of the clipped areas, the scaling rule, and each object scaled once a level."""

import numpy as np
import pyarrow as pa
import pytest

from rasterruns.functions import hilbert
from rasterruns.grid import GridSpec
from rasterruns.operators import approximate, filters, mbr, rasterize
from rasterruns.plans import join
from rasterruns.queries import spatial


def rings(rng, n, reach):
    """Stars with many points on grid lines, and squares of whole cells."""
    out = []
    for i in range(n):
        x, y = rng.integers(2 * reach, 5000, 2)
        if i % 4 == 0:
            a = 4 * int(rng.integers(1, reach // 4))
            out.append(np.array([[0, 0], [a, 0], [a, a], [0, a]])[:: 1 if i % 8 else -1] + [x // 4 * 4, y // 4 * 4])
            continue
        turn, far = np.linspace(0, 2 * np.pi, 11)[:-1] + 0.1, rng.integers(reach // 3, reach, 10)
        out.append(np.stack([x + (far * np.cos(turn)).astype(int) // 2 * 2, y + (far * np.sin(turn)).astype(int) // 2 * 2], 1))
    return out


def rows(rs, max_cells=750):
    """(oid, ring, k) as the stage over tiles has them."""
    k = []
    for r in rs:
        lo, hi = r.min(0), r.max(0)
        k.append(next(t for t in range(22) if np.prod((hi >> t) - (lo >> t) + 1) <= max_cells))
    return pa.RecordBatch.from_arrays([pa.array(np.arange(len(rs))), pa.array([r.ravel().tolist() for r in rs], pa.list_(pa.int32())), pa.array(np.array(k, np.int32))], names=["oid", "ring", "k"])


def built(batch, windows):
    got = pa.Table.from_batches(list(approximate.raster_rows(windows=windows)(iter([batch])))).combine_chunks().to_batches()[0]
    return got.take(pa.array(np.argsort(got.column("oid").to_numpy(), kind="stable")))


@pytest.mark.parametrize("cell", [1, 4, 7, 16])
def test_window_types_equal_clipped_areas(cell):
    rs = rings(np.random.default_rng(cell), 40, 60)
    b = rasterize.Batch(np.concatenate(rs), np.concatenate([[0], np.cumsum([len(r) for r in rs])]), GridSpec(14, cell=cell))
    x0, y0, w, _, off, kind = rasterize.window_types(b)
    at = np.flatnonzero(kind)
    o = np.searchsorted(off, at, "right") - 1
    y, x = np.divmod(at - off[o], w[o])
    got = sorted(zip(o.tolist(), hilbert.encode(x + x0[o], y + y0[o], 14).tolist(), kind[at].tolist(), strict=True))
    o, h, _, kind = rasterize.coverage(b)
    assert got == list(zip(o.tolist(), h.tolist(), kind.tolist(), strict=True))
    assert set(kind.tolist()) == {1, 2, 3}


@pytest.mark.parametrize("predicate", ["intersects", "within"])
def test_windows_give_the_verdicts_of_cell_lists(predicate):
    rng = np.random.default_rng(7)
    small, large = rows(rings(rng, 60, 40)), rows(rings(rng, 30, 900) + rings(rng, 30, 30))
    i, j = (x.ravel() for x in np.meshgrid(np.arange(small.num_rows), np.arange(large.num_rows)))
    zero = pa.array(np.zeros(len(i), np.int64))
    left, right = (i, j) if predicate == "within" else (j, i)
    ids = pa.RecordBatch.from_arrays([zero, pa.array(left), pa.array(right)], names=["tile_id", "rid", "sid"])
    kernel, a, b = filters.raster_kernel(predicate), built(small, True), built(large, True)
    half = len(i) // 2
    got = [v for x in (0, half) for v in kernel(ids.slice(x, half), a, i[x : x + half], b, j[x : x + half]).column("verdict").to_pylist()]
    p, q = (built(x, False).take(pa.array(at)) for x, at in ((small, i), (large, j)))
    r, s = (p, q) if predicate == "within" else (q, p)
    plain = pa.RecordBatch.from_arrays([*ids.columns, *(x.column(c) for x in (r, s) for c in ("k", "cells"))], names=[*ids.schema.names, "r_k", "r_cells", "s_k", "s_cells"])
    of_lists = {"intersects": filters.raster_result, "within": filters.raster_within_result}[predicate]
    assert got == of_lists(plain).column("verdict").to_pylist()
    assert len(set(got)) == 3


def test_objects_are_scaled_once_a_level(monkeypatch):
    """A later chunk of pairs of the same tables scales nothing again."""
    rng = np.random.default_rng(3)
    small, large = built(rows(rings(rng, 50, 40)), True), built(rows(rings(rng, 20, 900)), True)
    i, j = (x.ravel() for x in np.meshgrid(np.arange(50), np.arange(20)))
    ids = pa.RecordBatch.from_arrays([pa.array(np.zeros(len(i), np.int64)), pa.array(i), pa.array(j)], names=["tile_id", "rid", "sid"])
    made, coarsen = [], filters.Windows._coarsen
    monkeypatch.setattr(filters.Windows, "_coarsen", lambda self, rows, t: (made.extend((id(self), x, t) for x in rows.tolist()), coarsen(self, rows, t))[1])
    kernel = filters.raster_kernel("intersects")
    for a in range(0, len(i), 100):
        kernel(ids.slice(a, 100), small, i[a : a + 100], large, j[a : a + 100])
    assert made and len(made) == len(set(made))


def test_a_join_by_local_rasters_profiles_each_layer_once(spark, sf_dir, monkeypatch):
    a, b = (spatial.layer(spark, sf_dir, x).select("*") for x in ("sites", "ponds"))
    made, real = [], mbr.Profile
    monkeypatch.setattr(mbr, "Profile", lambda *x: (made.append(x), real(*x))[1])
    join.spatial_join(a, b, method="local_raster", grid=GridSpec(11))
    assert len(made) == 2


def test_centres_are_computed_by_batch(spark, sf_dir):
    """No hash is a Column expression (each repeats its argument four times), and the stage reads coordinates without a lambda."""
    from rasterruns.sources.layers import load_layer

    got = {x: load_layer(spark, sf_dir, x) for x in ("ponds", "parks")}
    for df in got.values():
        assert "2246822519" not in df._jdf.queryExecution().optimizedPlan().toString()
    a, b = (spatial.layer(spark, sf_dir, x) for x in ("sites", "ponds"))
    plan = join.box_verdicts(a, b, method="local_raster")._jdf.queryExecution().optimizedPlan().toString()
    assert ".x, ring#" in plan and "MapInArrow" in plan
