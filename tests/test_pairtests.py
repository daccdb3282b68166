"""The batch predicates equal the predicates of single pairs, touching boundaries and degenerate paths included."""

import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rasterruns.functions import codec, geometry, lists, pairtests
from rasterruns.operators import approximate, filters


def star(rnd, n, at, size):
    t = 2 * np.pi * (np.arange(n) + 0.5) / n
    r = rnd.uniform(0.4, 1.0, n) * size
    return np.stack([at[0] + r * np.cos(t), at[1] + r * np.sin(t)], 1).round().astype(np.int64)


def shapes(rings, closed=True):
    off = np.concatenate([[0], np.cumsum([len(r) for r in rings])]).astype(np.int64)
    return pairtests.Shapes(np.concatenate(rings) if rings else np.zeros((0, 2), np.int64), off, closed)


@pytest.mark.parametrize("seed,spread", [(0, 60), (1, 12), (2, 200)])
def test_batches_equal_single_pairs(seed, spread, monkeypatch):
    monkeypatch.setattr(pairtests, "_EDGES", 50)
    monkeypatch.setattr(pairtests, "_PAIRS", 70)
    rnd = np.random.default_rng(seed)
    large = [star(rnd, rnd.integers(5, 30), rnd.integers(80, 160, 2), 60) for _ in range(6)] + [np.array([[100, 100], [140, 100], [140, 140], [100, 140]])]
    small = [star(rnd, rnd.integers(3, 9), 120 + rnd.integers(-spread, spread + 1, 2), rnd.integers(4, 25)) for _ in range(150)]
    small += [np.array(r) for r in ([[110, 100], [120, 100], [115, 110]], [[140, 110], [150, 110], [150, 120]], [[100, 100], [140, 100], [140, 140], [100, 140]], [[140, 140], [150, 140], [150, 150]], [[105, 100], [130, 120], [105, 140]], [[90, 90], [200, 90], [200, 200], [90, 200]])]
    at = rnd.integers(0, len(large), len(small))
    at[-6:] = len(large) - 1
    s, g = shapes(small), shapes(large)
    assert pairtests.intersects(s, g, at).tolist() == [geometry.polygons_intersect(r, large[k]) for r, k in zip(small, at, strict=True)]
    assert pairtests.within(s, g, at).tolist() == [geometry.polygon_within(r, large[k]) for r, k in zip(small, at, strict=True)]
    paths = [np.cumsum(rnd.integers(-9, 10, (rnd.integers(1, 7), 2)), 0) + 120 + rnd.integers(-spread, spread + 1, 2) for _ in small]
    want = [geometry.line_intersects(p, large[k]) for p, k in zip(paths, at, strict=True)]
    single = [len(p) == 1 for p in paths]
    got = pairtests.line_meets(shapes(paths, False), g, at).tolist()
    assert [x for x, one in zip(got, single, strict=True) if not one] == [x for x, one in zip(want, single, strict=True) if not one]


def test_empty_rows_relate_to_nothing():
    none = np.zeros((0, 2), np.int64)
    square = np.array([[0, 0], [9, 0], [9, 9], [0, 9]])
    s, g = shapes([none, square, none]), shapes([square, none])
    at = np.array([0, 0, 1])
    assert pairtests.intersects(s, g, at).tolist() == [False, True, False]
    assert pairtests.within(s, g, at).tolist() == [False, True, False]


@settings(max_examples=60, deadline=None)
@given(seed=st.integers(0, 10_000))
def test_convex_batches_equal_single_pairs(seed):
    rnd = random.Random(seed)
    point = lambda: [rnd.randint(1, 30), rnd.randint(1, 30)]
    hulls = [geometry.convex_hull(np.array([point() for _ in range(rnd.randint(1, 9))])) for _ in range(40)] + [np.zeros((0, 2), np.int64)]
    sides = [[rnd.choice(hulls) for _ in range(30)] for _ in "ab"]
    a, b = (pairtests.Convex.read(pa.array([h.ravel().tolist() for h in side], pa.list_(pa.int64()))) for side in sides)
    some = [len(x) > 0 and len(y) > 0 for x, y in zip(*sides, strict=True)]
    assert pairtests.convex_apart(a, b).tolist() == [ok and geometry.convex_apart(x, y) for ok, x, y in zip(some, *sides, strict=True)]
    assert pairtests.convex_sticks_out(a, b).tolist() == [ok and geometry.convex_sticks_out(x, y) for ok, x, y in zip(some, *sides, strict=True)]


@settings(max_examples=60, deadline=None)
@given(seed=st.integers(0, 10_000), at_once=st.sampled_from([1, 7, 1_000_000]))
def test_words_hold_the_codes_of_common_cells(seed, at_once):
    """Aligned words against codes looked up cell by cell, for long runs at any shift, compressed or not."""
    rnd = random.Random(seed)

    def side(n: int, name: str):
        rows, runs, code = [], [], []
        for _ in range(n):
            at, cells, ends, data = rnd.randint(0, 40), {}, [], b""
            for _ in range(rnd.randint(0, 6)):
                size = rnd.choice([1, 2, 3, 18, 19, 20, 57, 130])
                kind = np.array([rnd.randint(1, 3) for _ in range(size)])
                cells |= {at + k: approximate.CODES[name][t] for k, t in enumerate(kind.tolist())}
                data += approximate.pack_codes(kind, np.zeros(size, np.int64), np.array([size]), name)[0].tobytes()
                ends += [at, at + size]
                at += size + rnd.randint(1, 60)
            rows.append(cells), runs.append(ends), code.append(data)
        return rows, pa.array(runs, pa.list_(pa.int64())), pa.array(code, pa.binary())

    (r, r_runs, r_code), (s, s_runs, s_code) = side(20, "R"), side(5, "S")
    at = np.array([rnd.randrange(5) for _ in r])
    packed = codec.encode(*lists.flat(r_runs)), codec.deflate(r_code)
    assert codec.inflate(packed[1]).equals(r_code)
    for mine in ((r_runs, r_code), packed):
        got: dict[int, list] = {}
        for row, p, q, used in filters.common_words(mine, (s_runs, s_code), at, at_once):
            for i, x, y, u in zip(row.tolist(), p.tolist(), q.tolist(), used.tolist(), strict=True):
                n = u.bit_count() // 3
                got.setdefault(i, []).extend((x >> 3 * (18 - k) & 7, y >> 3 * (18 - k) & 7) for k in range(n))
        for i, cells in enumerate(r):
            other = s[at[i]]
            assert got.get(i, []) == [(cells[h], other[h]) for h in sorted(cells.keys() & other.keys())]


@settings(max_examples=40, deadline=None)
@given(seed=st.integers(0, 10_000))
def test_pairs_of_table_rows_equal_pair_by_pair(seed):
    """Rings long enough for many strips; small rows stand once in the table however many pairs they have."""
    rng = np.random.default_rng(seed)
    stars = lambda n, size, r: [ring(rng, size, r) for _ in range(n)]
    small, large = stars(6, 9, 40), stars(3, 200, 160)
    own, at = (x.ravel() for x in np.meshgrid(np.arange(6), np.arange(3)))
    s, g = shapes(small), shapes(large)
    strips = g.strips
    assert (strips.n == pairtests.STRIPS).all() and sorted(strips.edges[strips.start[0] :].tolist()) == list(range(600))
    assert pairtests.intersects(s, g, at, own).tolist() == [geometry.polygons_intersect(small[i], large[k]) for i, k in zip(own, at, strict=True)]
    assert pairtests.within(s, g, at, own).tolist() == [geometry.polygon_within(small[i], large[k]) for i, k in zip(own, at, strict=True)]


def ring(rng, n: int, r: int) -> np.ndarray:
    """A star around a random centre."""
    turn = 2 * np.pi * np.arange(n) / n
    radius = r * rng.uniform(0.6, 1, n)
    return np.round(rng.integers(200, 500, 2) + np.stack([radius * np.cos(turn), radius * np.sin(turn)], 1)).astype(np.int64)


@pytest.mark.parametrize("seed", range(4))
def test_strips_settle_points_and_boxes(seed, monkeypatch):
    """A strip's edges decide a point as the whole ring does; a box beside a ring's strips shares no point with it."""
    monkeypatch.setattr(pairtests, "_EDGES", 50)
    rng = np.random.default_rng(seed)
    rings = [ring(rng, n, r) for n, r in ((3, 40), (20, 90), (256, 150))] + [np.array([[200, 200], [300, 200], [300, 203], [200, 203]])]
    g = shapes(rings)
    at = rng.integers(0, len(rings), 600)
    x, y = rng.integers(0, 700, (2, 600))
    got = g.strips.inside(x, y, at)
    cross = [sum((a[1] > q) != (b[1] > q) and ((b[0] - a[0]) * (q - a[1]) - (p - a[0]) * (b[1] - a[1]) > 0) == (b[1] > a[1]) for a, b in zip(rings[k], np.roll(rings[k], -1, 0), strict=True)) for p, q, k in zip(x, y, at, strict=True)]
    assert got.tolist() == [n % 2 == 1 for n in cross] and got.any()
    box = np.stack([x, y, x + rng.integers(0, 60, 600), y + rng.integers(0, 60, 600)], 1)
    beside = g.strips.beside(box, at)
    meets = [geometry.polygons_intersect(b[[0, 1, 2, 1, 2, 3, 0, 3]].reshape(4, 2), rings[k]) for b, k in zip(box, at, strict=True)]
    assert beside.any() and not (beside & np.array(meets)).any()


def test_edges_are_compared_only_where_points_leave_it_open(monkeypatch):
    rng = np.random.default_rng(3)
    g = shapes([ring(rng, 256, 150)])
    middle = g.pts.mean(0).astype(np.int64)
    square = np.array([[0, 0], [9, 0], [9, 9], [0, 9]])
    half = g.pts[g.pts[:, 0].argmax()] - [0, 4] + square - [9, 0]  # has the ring's rightmost point on its side
    small = shapes([middle + square, middle + square + [400, 0], half])
    seen, close = [], pairtests._close_edges
    monkeypatch.setattr(pairtests, "_close_edges", lambda s, own, large, at: (seen.extend(own.tolist()), close(s, own, large, at))[1])
    assert pairtests.intersects(small, g, np.zeros(3, np.int64)).tolist() == [True, False, True]
    assert set(seen) <= {2}


@pytest.mark.parametrize("seed,size", [(0, 12), (1, 40), (2, 3)])
def test_hull_verdicts_of_table_rows_equal_single_pairs(seed, size, monkeypatch):
    """Boxes and corners settle most pairs of hulls before sides are compared, degenerate hulls not; verdicts stay."""
    rng = np.random.default_rng(seed)
    rings = lambda n, r: [ring(rng, rng.integers(3, size + 1), r) for _ in range(n)] + [np.array([[300, 300]]), np.array([[300, 300], [330, 330]]), np.array([[340, 340], [350, 350]]), np.zeros((0, 2), np.int64)]
    sides = [[geometry.convex_hull(r).reshape(-1, 2) for r in rings(n, r)] for n, r in ((60, 12), (8, 120))]
    tables = [pa.RecordBatch.from_arrays([pa.array([f(h).ravel().tolist() for h in x], pa.list_(kind)) for f, kind in ((geometry.five_corners, pa.float64()), (lambda h: h, pa.int64()))], names=["corners", "hull"]) for x in sides]
    i, j = (x.ravel() for x in np.meshgrid(*(np.arange(t.num_rows) for t in tables)))
    ids = pa.RecordBatch.from_arrays([pa.array(np.zeros(len(i), np.int32)), pa.array(i), pa.array(j)], names=["tile_id", "rid", "sid"])
    compared, apart = [], pairtests.convex_apart
    monkeypatch.setattr(pairtests, "convex_apart", lambda a, b, p, q: (compared.append(len(p)), apart(a, b, p, q))[1])
    got = filters.hull_kernel("intersects", "right")(ids, tables[0], i, tables[1], j).column("verdict").to_pylist()
    want = [len(sides[0][a]) > 0 and len(sides[1][b]) > 0 and geometry.convex_apart(sides[0][a], sides[1][b]) for a, b in zip(i, j, strict=True)]
    assert got == ["miss" if x else "unsure" for x in want] and {*got} == {"miss", "unsure"}
    assert sum(compared) < len(i)
