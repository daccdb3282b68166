"""Kernels against slow references: curve, cells, constructions, lists, codes, predicates."""

import math
import random
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rasterruns.functions import codec, geometry, hilbert, lists
from rasterruns.grid import GridSpec
from rasterruns.operators import approximate, filters, rasterize


def star(rnd, n, cx, cy, r):
    at = [2 * math.pi * (i + 0.5) / n for i in range(n)]
    return np.array([[int(cx + math.cos(a) * q), int(cy + math.sin(a) * q)] for a, q in zip(at, [r * rnd.randint(600, 1000) / 1000 for _ in range(n)], strict=True)], np.int64)


def rings(seed, n=60):
    rnd = random.Random(seed)
    out = [star(rnd, rnd.randint(5, 20), 128, 128, rnd.randint(10, 110)) for _ in range(n)]
    out += [np.array(x, np.int64) for x in ([[16, 16], [64, 16], [64, 64], [16, 64]], [[64, 64], [16, 64], [16, 16], [64, 16]], [[20, 20], [22, 20], [21, 22]], [[40, 8], [41, 120], [42, 8]])]
    return out


def batch(rs, grid):
    return rasterize.Batch(np.concatenate(rs), np.concatenate([[0], np.cumsum([len(r) for r in rs])]), grid)


def ids(lists_, i):
    v, o = lists_
    return {x for k in range(o[i], o[i + 1], 2) for x in range(v[k], v[k + 1])}


@pytest.mark.parametrize("order", range(1, 9))
def test_curve(order):
    n = 1 << order
    x, y = (a.ravel() for a in np.meshgrid(np.arange(n), np.arange(n)))
    h = hilbert.encode(x, y, order)
    assert sorted(h) == list(range(n * n))
    bx, by = hilbert.decode(np.arange(n * n), order)
    assert (np.abs(np.diff(bx)) + np.abs(np.diff(by)) == 1).all()
    for low in range(1, order):
        assert (hilbert.encode(x >> (order - low), y >> (order - low), low) == h >> (2 * (order - low))).all()
    if order == 3:
        (ax, cx), (ay, cy) = hilbert.decode(np.array([33, 52]), 3)
        assert abs(ax - cx) + abs(ay - cy) == 1


def enters(e, cx, cy, s):
    """Whether a segment has a point in a half-open cell, in rationals."""
    x0, y0, x1, y1 = e
    lo, hi = (Fraction(0), True), (Fraction(1), True)
    for a, d, low in ((x0, x1 - x0, cx * s), (y0, y1 - y0, cy * s)):
        if d == 0:
            if not low <= a < low + s:
                return False
            continue
        t = [(Fraction(low - a, d), True), (Fraction(low + s - a, d), False)]
        if d < 0:
            t.reverse()
        if t[0][0] > lo[0] or t[0][0] == lo[0] and not t[0][1]:
            lo = t[0]
        if t[1][0] < hi[0] or t[1][0] == hi[0] and not t[1][1]:
            hi = t[1]
    return lo[0] < hi[0] or lo[0] == hi[0] and lo[1] and hi[1]


def test_cells_against_rationals():
    grid, rs = GridSpec(5, cell=8), rings(1, 6)
    got = rasterize.onestep(batch(rs, grid))
    for i, r in enumerate(rs):
        e = geometry.edges(r, True).tolist()
        for cx in range(32):
            for cy in range(32):
                h = int(hilbert.encode([cx], [cy], 5)[0])
                edge = any(enters(x, cx, cy, 8) for x in e)
                core = not edge and bool(geometry.inside(np.array([cx * 8 + 4]), np.array([cy * 8 + 4]), r)[0])
                assert (h in ids(got["cover"], i), h in ids(got["core"], i)) == (edge or core, core)


@pytest.mark.parametrize("cell,order", [(8, 5), (1, 8), (3, 7)])
def test_constructions_agree(cell, order):
    rs = rings(2)
    got = {k: f(batch(rs, GridSpec(order, cell=cell))) for k, f in rasterize.METHODS.items()}
    ref = got["onestep_pip"]
    for k, g in got.items():
        for c in ("cover", "core"):
            assert np.array_equal(g[c][0], ref[c][0]) and np.array_equal(g[c][1], ref[c][1]), (k, c)
    assert (got["onestep_neighbours"]["n_pip"] <= ref["n_pip"]).all() and (ref["n_pip"] == ref["n_gaps"]).all()
    assert (ref["n_gaps"] <= ref["n_edge"] - 1).all()
    assert got["onestep_neighbours"]["n_pip"].sum() < 0.7 * ref["n_pip"].sum()
    for v, o in (ref["cover"], ref["core"]):
        for i in range(len(o) - 1):
            assert (np.diff(v[o[i] : o[i + 1]]) > 0).all()


def test_coverage_sums_to_area_and_ties_are_exact():
    rs = rings(3) + [np.array([[8, 8], [16, 8], [16, 12], [8, 12]]), np.array([[8, 8], [16, 8], [8, 16]])]
    o, h, share, kind = rasterize.coverage(batch(rs, GridSpec(5, cell=8)))
    area = np.bincount(o, share * 64)
    true = [abs(sum(int(a[0]) * int(b[1]) - int(b[0]) * int(a[1]) for a, b in zip(r, np.roll(r, -1, axis=0), strict=True))) / 2 for r in rs]
    assert np.allclose(area, true)
    half = kind[(o >= len(rs) - 2) & (share == 0.5)]
    assert len(half) == 2 and (half == rasterize.WEAK).all()  # one half is not above one half
    a, b = rasterize.coverage(batch(rs, GridSpec(5, cell=8)), True), (o, h, share, kind)
    assert all(np.array_equal(x, y) for x, y in zip(a, b, strict=True))


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.lists(st.integers(0, 60), max_size=8, unique=True), st.lists(st.integers(0, 60), max_size=8, unique=True)), min_size=1, max_size=6))
def test_list_kernels(pairs):
    def column(k):
        rows = [sorted(p[k])[: len(p[k]) // 2 * 2] for p in pairs]
        rows = [[v for a, b in zip(r[0::2], r[1::2], strict=True) for v in (a, b)] for r in rows]
        return np.array([v for r in rows for v in r], np.int64), np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)

    a, b = column(0), column(1)
    over, inside, low = lists.overlap(a, b), lists.contained(a, b), lists.coarsen(a, 1)
    coded = codec.encode(*a), codec.encode(*b)
    v, o = codec.decode(coded[0])
    assert np.array_equal(v, a[0]) and np.array_equal(o, a[1])
    for i in range(len(pairs)):
        x, y = ids(a, i), ids(b, i)
        assert over[i] == bool(x & y)
        assert codec.cursors_overlap(codec.Cursor(coded[0][i].as_py(), 1), codec.Cursor(coded[1][i].as_py(), 2)) == bool(x & y)
        assert ids(low, i) == {h >> 2 for h in x}
        if all(b[0][k + 1] < b[0][k + 2] for k in range(b[1][i], b[1][i + 1] - 2, 2)):
            assert inside[i] == (x <= y)


def test_byte_sizes():
    assert codec.sizes(np.array([0, 127, 128, 16383, 16384, 1 << 21, 1 << 28])).tolist() == [1, 1, 2, 2, 3, 4, 5]


def test_codes():
    r, s = approximate.CODES["R"], approximate.CODES["S"]
    for a in (1, 2, 3):
        assert r[a] ^ approximate.SWAP == s[a]
        for b in (1, 2, 3):
            assert bool(r[a] & s[b]) == (a == 3 or b == 3 or a == b == 2)
    data, start = approximate.pack_codes(np.array([1, 2, 1]), np.zeros(3, np.int64), np.array([3]), "R")
    assert "".join(map(str, np.unpackbits(data)[:9])) == "100101100" and start.tolist() == [0, 2]
    pack = lambda bits: int(bits.ljust(16, "0"), 2).to_bytes(2, "big")
    assert not filters.aligned_and(pack("100101101101"), pack("100100101100"), 6, 6, swap=True)
    assert filters.aligned_and(pack("100011"), pack("101"), 3, 3)


@settings(max_examples=150, deadline=None)
@given(st.integers(0, 10_000))
def test_exact_predicates_on_small_stars(seed):
    rnd = random.Random(seed)
    a, b = (star(rnd, rnd.randint(3, 8), rnd.randint(20, 40), rnd.randint(20, 40), rnd.randint(4, 18)) for _ in range(2))
    if not (geometry.is_simple(a) and geometry.is_simple(b)):
        return
    grid = np.stack(np.meshgrid(np.arange(0, 61), np.arange(0, 61)), -1).reshape(-1, 2)
    ina, inb = geometry.covers(grid, a), geometry.covers(grid, b)
    if (ina & inb).any():
        assert geometry.polygons_intersect(a, b)
    within = geometry.polygon_within(a, b)
    if within:
        assert geometry.polygons_intersect(a, b) and not (ina & ~inb).any()
    assert geometry.polygons_intersect(a, b) == geometry.polygons_intersect(b, a)
    assert geometry.polygon_within(a, a)
    h, k = geometry.convex_hull(a), geometry.convex_hull(b)
    f, g = geometry.five_corners(h), geometry.five_corners(k)
    assert len(f) <= max(5, 3) or len(h) > 5
    if geometry.convex_apart(f, g) or geometry.convex_apart(h, k):
        assert not geometry.polygons_intersect(a, b)
    if geometry.convex_sticks_out(h.astype(float), g) or geometry.convex_sticks_out(h.astype(float), k.astype(float)):
        assert not within
    assert not geometry.convex_sticks_out(h.astype(float), f)


def test_degenerate_predicates():
    square = np.array([[10, 10], [20, 10], [20, 20], [10, 20]])
    p = lambda *x: np.array(x, np.int64)
    assert geometry.polygons_intersect(square, p((20, 20), (30, 20), (30, 30)))  # one point
    assert geometry.polygons_intersect(square, p((20, 10), (30, 10), (30, 20), (20, 20)))  # shared side
    assert not geometry.polygons_intersect(square, p((21, 10), (30, 10), (30, 20)))
    assert geometry.polygons_intersect(square, p((12, 12), (14, 12), (14, 14)))  # nested
    assert geometry.polygon_within(p((10, 10), (15, 10), (12, 15)), square)  # side on side
    notched = p((10, 10), (20, 10), (20, 20), (15, 12), (10, 20))
    assert not geometry.polygon_within(p((10, 10), (20, 10), (20, 20), (10, 20)), notched)
    assert not geometry.polygon_within(p((10, 20), (10, 10), (20, 20)), notched)  # a side across the notch
    assert geometry.line_intersects(p((0, 0), (10, 10)), square) and geometry.line_intersects(p((12, 12), (13, 13)), square)
    assert geometry.line_intersects(p((20, 20), (20, 20)), square) and not geometry.line_intersects(p((0, 0), (9, 30)), square)


def test_line_cells_of_a_point_path():
    b = rasterize.Batch(np.array([[5, 5], [5, 5], [7, 9]]), np.array([0, 2, 3]), GridSpec(5, cell=8), closed=False)
    o, h = rasterize.edge_ids(b)
    assert o.tolist() == [0, 1]


def test_high_orders_keep_objects_apart():
    rs = rings(5, 3)
    got = rasterize.onestep(batch(rs, GridSpec(30, cell=1)).part(0, 1))
    assert len(got["cover"][0])
    with pytest.raises(ValueError):
        GridSpec(31)
    with pytest.raises(ValueError):
        GridSpec(25)


def test_upscale_rule():
    key, kind = filters.upscale(np.zeros(6, np.int64), np.array([0, 0, 1, 1, 2, 3]), np.array([0, 1, 0, 1, 0, 0]), np.array([3, 3, 3, 3, 3, 2]), np.ones(6, np.int64))
    assert kind.tolist() == [3, 1]
    assert isinstance(pa.array(key), pa.Array)


def test_exact_cell_areas_equal_clipping():
    """Areas of random rings in cells, against clipping at the cell's four sides; shares add up to the ring."""
    from fractions import Fraction

    from rasterruns.operators import rasterize

    def clipped(ring, x0, y0, s):
        pts = [(Fraction(x), Fraction(y)) for x, y in ring]
        for axis, limit, turn in ((0, x0, 1), (0, x0 + s, -1), (1, y0, 1), (1, y0 + s, -1)):
            out = []
            for q, p in zip(pts[-1:] + pts[:-1], pts, strict=True):
                a, c = turn * (q[axis] - limit), turn * (p[axis] - limit)
                if (a >= 0) != (c >= 0):
                    out.append(tuple(q[k] + a / (a - c) * (p[k] - q[k]) for k in (0, 1)))
                if c >= 0:
                    out.append(p)
            pts = out
        return abs(sum(q[0] * p[1] - p[0] * q[1] for q, p in zip(pts[-1:] + pts[:-1], pts, strict=True))) / 2

    rng = np.random.default_rng(11)
    for _ in range(40):
        a = np.sort(rng.random(7)) * 2 * np.pi
        ring = [(int(40 + r * np.cos(t)), int(40 + r * np.sin(t))) for r, t in zip(rng.integers(3, 30, 7), a, strict=True)]
        for ring_ in (ring, ring[::-1]):
            got = {(x, y): rasterize._clip_exact(ring_, x, y, 8) for x in range(0, 80, 8) for y in range(0, 80, 8)}
            assert all(v == clipped(ring_, *k, 8) for k, v in got.items())


def test_exact_areas_touch_few_edges(monkeypatch):
    """Edges outside the cell's rows or left of it cost no rational: a ring of many edges takes a handful."""
    from rasterruns.operators import rasterize

    made = []
    real = rasterize.Fraction
    monkeypatch.setattr(rasterize, "Fraction", lambda *a: made.append(a) or real(*a))
    t = np.linspace(0, 2 * np.pi, 400, endpoint=False)
    ring = [(int(x), int(y)) for x, y in zip(1000 + 900 * np.cos(t), 1000 + 900 * np.sin(t), strict=True)]
    assert rasterize._clip_exact(ring, 1000, 1000, 16) == 256 and len(made) < 10


@pytest.mark.parametrize("table", [40, 2_000_000])
def test_hulls_and_corners_of_a_batch_equal_one_by_one(table, monkeypatch):
    """Empty, single, repeated and collinear points, and rings of unlike sizes; no object is built by itself any more."""
    rng = np.random.default_rng(5)
    rings = [np.zeros((0, 2), np.int64), np.array([[3, 4]]), np.array([[3, 4]] * 3), np.array([[1, 1], [5, 5], [3, 3]]), np.array([[7, 2], [7, 9], [7, 2]])]
    rings += [rng.integers(0, 12, (n, 2)) for n in rng.integers(1, 30, 60)]
    turn = 2 * np.pi * np.arange(90) / 90
    rings += [np.stack([np.cos(turn), np.sin(turn)], 1)[:n] * rng.uniform(5e4, 9e4) // 1 + 200_000 for n in (7, 30, 90)]
    rings = [r.astype(np.int64) for r in rings]
    hulls = [geometry.convex_hull(r).reshape(-1, 2) for r in rings]
    fives = [geometry.five_corners(h) for h in hulls]
    monkeypatch.setattr(geometry, "_TABLE", table)
    for one in ("convex_hull", "five_corners"):
        monkeypatch.setattr(geometry, one, lambda *_: pytest.fail("built by itself"))
    column = pa.array([[{"x": x, "y": y} for x, y in r.tolist()] for r in rings], pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())])))
    batch = pa.RecordBatch.from_arrays([pa.array(np.arange(len(rings))), column], names=["oid", "ring"])
    (got,) = approximate.hull_rows(iter([batch]))
    assert got.column("hull").to_pylist() == [h.ravel().tolist() for h in hulls]
    assert got.column("corners").to_pylist() == [f.ravel().tolist() for f in fives]
