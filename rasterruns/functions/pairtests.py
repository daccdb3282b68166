"""Exact predicates for a whole batch of pairs at once.

The pairs of a batch point to a few large rows.  A pair's large edges are
narrowed to those that meet the small object's box (by strips first, as those
also decide the parity of a point), the rest is compared edge by edge in exact
integers.  Chunks bound the memory whatever the sizes.
"""

from __future__ import annotations

from functools import cached_property

import numpy as np
import pyarrow as pa

from rasterruns.functions import geometry

#: Large edges looked at, and edge pairs compared, at once: what a core's cache holds.
_EDGES, _PAIRS = 131_072, 131_072
#: Most strips an object's edges are looked up by.
STRIPS = 64
#: Points tried before edges are compared, as parts of the way round, and the share of pairs that one must settle for the next to be tried.
POINTS, LEAST = (0, 0.5, 0.25, 0.75), 0.125


class Shapes:
    """Edges of many rings (or paths) with the boxes of edges and objects."""

    def __init__(self, pts: np.ndarray, off: np.ndarray, closed: bool = True):
        size = np.diff(off)
        nxt = np.arange(len(pts)) + 1
        some = size > 0
        nxt[off[1:][some] - 1] = off[:-1][some] if closed else off[1:][some] - 1  # a path ends in a point
        self.pts, self.off = pts, off
        self.x0, self.y0 = np.ascontiguousarray(pts[:, 0]), np.ascontiguousarray(pts[:, 1])
        self.x1, self.y1 = self.x0[nxt] if len(pts) else self.x0, self.y0[nxt] if len(pts) else self.y0
        self.left, self.right = np.minimum(self.x0, self.x1), np.maximum(self.x0, self.x1)
        self.low, self.high = np.minimum(self.y0, self.y1), np.maximum(self.y0, self.y1)
        self.box = np.full((len(size), 4), [1, 1, 0, 0], np.int64)
        if some.any():
            at = off[:-1][some]
            self.box[some] = np.stack([np.minimum.reduceat(self.x0, at), np.minimum.reduceat(self.y0, at), np.maximum.reduceat(self.x0, at), np.maximum.reduceat(self.y0, at)], 1)

    def points(self, i: int) -> np.ndarray:
        return self.pts[self.off[i] : self.off[i + 1]]

    @cached_property
    def strips(self) -> Strips:
        return Strips(self)


class Strips:
    """Edges of each object by horizontal strips of equal height, half as many as edges, at most STRIPS.

    ``edges[reach[s] : reach[s + 1]]`` come from below into strip s;
    ``edges[start[s] : start[t + 1]]`` begin in the strips s to t of an object.
    So an object's edges that reach some heights are two stretches, none twice.
    A single strip's edges are the ``ends`` (x0, y0, x1, y1) ``each[s] : each[s + 1]``.
    """

    def __init__(self, shapes: Shapes):
        size = np.diff(shapes.off)
        self.n = np.clip(size // 2, 1, STRIPS)
        self.height = (shapes.box[:, 3] - shapes.box[:, 1]) // self.n + 1
        self.height[size == 0] = 1
        self.first = np.cumsum(self.n) - self.n
        self.bottom = shapes.box[:, 1]
        row = np.repeat(np.arange(len(size)), size)
        bottom = shapes.box[row, 1]
        low, high = ((y - bottom) // self.height[row] for y in (shapes.low, shapes.high))
        total = int(self.n.sum())
        edge, k = spread(high - low)
        later, begin = self.first[row[edge]] + low[edge] + 1 + k, self.first[row] + low
        self.edges = np.concatenate([edge[np.argsort(later, kind="stable")], np.argsort(begin, kind="stable")])
        self.reach = np.concatenate([[0], np.cumsum(np.bincount(later, minlength=total))])
        self.start = len(edge) + np.concatenate([[0], np.cumsum(np.bincount(begin, minlength=total))])
        strip = np.concatenate([later, begin])
        order = np.argsort(strip, kind="stable")
        edge = np.concatenate([edge, np.arange(len(row))])[order]
        self.each = np.concatenate([[0], np.cumsum(np.bincount(strip, minlength=total))])
        self.ends = np.stack([shapes.x0[edge], shapes.y0[edge], shapes.x1[edge], shapes.y1[edge]], 1)
        self.low, self.high = shapes.low[edge], shapes.high[edge]
        # each strip's least and greatest x, then those of 2, 4, ... strips from it on
        some = np.flatnonzero(np.diff(self.each))
        least, most = np.full(total, np.iinfo(np.int64).max), np.full(total, np.iinfo(np.int64).min)
        if len(some):
            least[some], most[some] = np.minimum.reduceat(shapes.left[edge], self.each[some]), np.maximum.reduceat(shapes.right[edge], self.each[some])
        self.least, self.most = [least], [most]
        for k in range(STRIPS.bit_length() - 1):
            for levels, f in ((self.least, np.minimum), (self.most, np.maximum)):
                levels.append(levels[-1].copy())
                levels[-1][: -(1 << k)] = f(levels[-2][: -(1 << k)], levels[-2][1 << k :])
        self.least, self.most = np.concatenate(self.least), np.concatenate(self.most)

    def of(self, at: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The strip of object ``at`` that holds height ``y``, or the nearest one."""
        return self.first[at] + np.clip((y - self.bottom[at]) // self.height[at], 0, self.n[at] - 1)

    def beside(self, boxes: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Whether all edges of object ``at`` that reach a box's heights lie to one side of the box."""
        low, high = self.of(at, boxes[:, 1]), self.of(at, boxes[:, 3])
        level = np.frexp(high - low + 1)[1].astype(np.int64) - 1
        base = level * len(self.each[1:])
        a, b = base + low, base + high + 1 - (1 << level)
        return (boxes[:, 2] < np.minimum(self.least[a], self.least[b])) | (boxes[:, 0] > np.maximum(self.most[a], self.most[b]))

    def inside(self, x: np.ndarray, y: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Whether point i lies inside ring ``at[i]`` (off its boundary); only the edges of the point's strip are looked at."""
        g = self.of(at, y)
        first, count = self.each[g], self.each[g + 1] - self.each[g]
        out = np.zeros(len(at), bool)
        for a, b in pieces(count, _EDGES):
            n = count[a:b]
            e = np.arange(int(n.sum())) + np.repeat(first[a:b] - (np.cumsum(n) - n), n)
            py = np.repeat(y[a:b], n)
            spans = np.flatnonzero((self.low[e] <= py) & (self.high[e] > py))
            q = np.repeat(np.arange(a, b), n)[spans]
            x0, y0, x1, y1 = self.ends[e[spans]].T
            side = (x1 - x0) * (py[spans] - y0) - (x[q] - x0) * (y1 - y0)
            out[a:b] = np.bincount(q[(side > 0) == (y1 > y0)] - a, minlength=b - a) % 2 == 1
        return out


def spread(count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each row as often as ``count`` says, and the place within its repeats."""
    owner = np.repeat(np.arange(len(count)), count)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)


def pieces(cost: np.ndarray, at_once: int):
    """Bounds of stretches of rows whose cost stays near ``at_once``."""
    cum, a = np.cumsum(cost), 0
    while a < len(cost):
        b = max(a + 1, int(np.searchsorted(cum, (cum[a - 1] if a else 0) + at_once, "right")))
        yield a, b
        a = b


def _turns(a: Shapes, i: np.ndarray, b: Shapes, j: np.ndarray) -> tuple[np.ndarray, ...]:
    """On which side of an edge of ``b`` the ends of ``a``'s lie, and the other way round."""
    ax, ay, bx, by = a.x0[i], a.y0[i], a.x1[i], a.y1[i]
    cx, cy, dx, dy = b.x0[j], b.y0[j], b.x1[j], b.y1[j]
    turn = lambda px, py, qx, qy, x, y: (qx - px) * (y - py) - (qy - py) * (x - px)
    return turn(ax, ay, bx, by, cx, cy), turn(ax, ay, bx, by, dx, dy), turn(cx, cy, dx, dy, ax, ay), turn(cx, cy, dx, dy, bx, by)


def _share(a: Shapes, i: np.ndarray, b: Shapes, j: np.ndarray) -> np.ndarray:
    """For pairs of edges whose boxes meet: they share a point."""
    p, q, r, s = _turns(a, i, b, j)
    return (np.minimum(p, q) <= 0) & (np.maximum(p, q) >= 0) & (np.minimum(r, s) <= 0) & (np.maximum(r, s) >= 0)


def _compare(a: Shapes, i: np.ndarray, b: Shapes, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For pairs of edges whose boxes meet: (they share a point, they cross in the inside of both)."""
    p, q, r, s = (np.sign(v) for v in _turns(a, i, b, j))
    return (p * q <= 0) & (r * s <= 0), (p * q < 0) & (r * s < 0)


def _close_edges(small: Shapes, own: np.ndarray, large: Shapes, at: np.ndarray):
    """Edges of each pair's large ring that reach the height of its small object's box.

    Yields (a, b, pair - a, edge) for stretches of pairs.  The rings' edges are
    looked up by strips, so that a long ring isn't read whole for every pair.
    """
    strips = large.strips
    low, high = small.box[own, 1], small.box[own, 3]
    g = [strips.first[at] + np.clip((y - large.box[at, 1]) // strips.height[at], 0, strips.n[at] - 1) for y in (low, high)]
    begin = np.stack([strips.reach[g[0]], strips.start[g[0]]], 1)
    count = np.stack([strips.reach[g[0] + 1], strips.start[g[1] + 1]], 1) - begin
    count[np.diff(large.off)[at] == 0] = 0
    for a, b in pieces(count.sum(1), _EDGES):
        half, k = spread(count[a:b].ravel())
        q, e = half >> 1, strips.edges[begin[a:b].ravel()[half] + k]
        keep = (large.high[e] >= low[a:b][q]) & (large.low[e] <= high[a:b][q])
        yield a, b, q[keep], e[keep]


def _crossings(x: np.ndarray, y: np.ndarray, q: np.ndarray, rings: Shapes, e: np.ndarray, n: int) -> np.ndarray:
    """How many of the edges ``e`` a ray from point ``q`` crosses, for each of ``n`` points."""
    py, y0, y1 = y[q], rings.y0[e], rings.y1[e]
    spans = np.flatnonzero((y0 > py) != (y1 > py))
    q, e, py, y0, y1 = q[spans], e[spans], py[spans], y0[spans], y1[spans]
    x0 = rings.x0[e]
    side = (rings.x1[e] - x0) * (py - y0) - (x[q] - x0) * (y1 - y0)
    return np.bincount(q[(side > 0) == (y1 > y0)], minlength=n)


def _edge_pairs(small: Shapes, own: np.ndarray, large: Shapes, q: np.ndarray, e: np.ndarray):
    """Pairs of edges whose boxes meet: (pair, small's edge, large's edge), for close edges ``e`` of pairs ``q``."""
    near = np.flatnonzero((large.right[e] >= small.box[own[q], 0]) & (large.left[e] <= small.box[own[q], 2]))
    q, e = q[near], e[near]
    first, size = small.off[:-1][own[q]], np.diff(small.off)[own[q]]
    for c, d in pieces(size, _PAIRS):
        r, k = spread(size[c:d])
        i, j = first[c:d][r] + k, e[c:d][r]
        meet = np.flatnonzero((small.right[i] >= large.left[j]) & (small.left[i] <= large.right[j]))
        r, i, j = r[meet], i[meet], j[meet]
        meet = np.flatnonzero((small.high[i] >= large.low[j]) & (small.low[i] <= large.high[j]))
        yield q[c:d][r[meet]], i[meet], j[meet]


def relate(small: Shapes, large: Shapes, at: np.ndarray, own: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per pair (row ``own[i]`` of ``small``, i by default, and row ``at[i]`` of ``large``): boundaries touch, cross properly, small's first point is inside."""
    n = len(at)
    own = np.arange(n) if own is None else own
    touch, cross, inside = np.zeros(n, bool), np.zeros(n, bool), np.zeros(n, bool)
    live = np.flatnonzero(np.diff(small.off)[own] > 0)
    own, at = own[live], at[live]
    for a, b, q, e in _close_edges(small, own, large, at):
        p = small.off[:-1][own[a:b]]
        inside[live[a:b]] = _crossings(small.x0[p], small.y0[p], q, large, e, b - a) % 2 == 1
        for r, i, j in _edge_pairs(small, own[a:b], large, q, e):
            share, proper = _compare(small, i, large, j)
            touch[live[a:b][r[share]]] = True
            cross[live[a:b][r[proper]]] = True
    return touch, cross, inside


def _first_inside(points: Shapes, which: np.ndarray, rings: Shapes, rows: np.ndarray) -> np.ndarray:
    """Whether the first point of object ``which[i]`` lies inside ring ``rows[i]`` (off its boundary)."""
    out = np.zeros(len(rows), np.int64)
    size = np.diff(rings.off)[rows]
    for a, b in pieces(size, _EDGES):
        own, k = spread(size[a:b])
        own += a
        e = rings.off[:-1][rows[own]] + k
        p = points.off[:-1][which[own]]
        px, py = points.x0[p], points.y0[p]
        spans = (rings.y0[e] > py) != (rings.y1[e] > py)
        own, e, px, py = own[spans], e[spans], px[spans], py[spans]
        side = (rings.x1[e] - rings.x0[e]) * (py - rings.y0[e]) - (px - rings.x0[e]) * (rings.y1[e] - rings.y0[e])
        out += np.bincount(own[(side > 0) == (rings.y1[e] > rings.y0[e])], minlength=len(rows))
    return out % 2 == 1


def _outside(small: Shapes, own: np.ndarray, large: Shapes, at: np.ndarray) -> np.ndarray:
    """The pairs of which no tried point of small's lies inside large."""
    left, size = np.arange(len(at)), np.diff(small.off)
    for part in POINTS:
        i = own[left]
        p = small.off[:-1][i] + (part * size[i]).astype(np.int64)
        tried, left = len(left), left[~large.strips.inside(small.x0[p], small.y0[p], at[left])]
        if tried - len(left) < tried * LEAST:
            break
    return left


def intersects(small: Shapes, large: Shapes, at: np.ndarray, own: np.ndarray | None = None) -> np.ndarray:
    """At least one common point of closed polygons: boundaries touch, or one holds the other.

    Edges are compared only for the pairs that small's box and some of its points don't settle.
    """
    own = np.arange(len(at)) if own is None else own
    out = np.zeros(len(at), bool)
    live = np.flatnonzero((np.diff(small.off)[own] > 0) & (np.diff(large.off)[at] > 0))
    live = live[~large.strips.beside(small.box[own[live]], at[live])]
    out[live] = True
    live = live[_outside(small, own[live], large, at[live])]
    out[live] = False
    own, at = own[live], at[live]
    for a, b, q, e in _close_edges(small, own, large, at):
        hit = np.zeros(b - a, bool)
        for r, i, j in _edge_pairs(small, own[a:b], large, q, e):
            hit[r[_share(small, i, large, j)]] = True
        out[live[a:b]] = hit
    p, box = large.off[:-1][at], small.box[own]
    x, y = large.x0[p], large.y0[p]
    rest = np.flatnonzero(~out[live] & (x >= box[:, 0]) & (x <= box[:, 2]) & (y >= box[:, 1]) & (y <= box[:, 3]))
    out[live[rest]] = _first_inside(large, at[rest], small, own[rest])
    return out


def within(small: Shapes, large: Shapes, at: np.ndarray, own: np.ndarray | None = None) -> np.ndarray:
    """Every point of the small polygon in the large one; boundaries that touch without crossing are settled one by one."""
    own = np.arange(len(at)) if own is None else own
    a, b = small.box[own], large.box[at]
    out = (a[:, 0] >= b[:, 0]) & (a[:, 2] <= b[:, 2]) & (a[:, 1] >= b[:, 1]) & (a[:, 3] <= b[:, 3]) & (np.diff(small.off)[own] > 0) & (np.diff(large.off)[at] > 0)
    touch, cross, inside = relate(small, large, at, own)
    out &= ~cross & (touch | inside)
    for i in np.flatnonzero(out & touch).tolist():
        out[i] = geometry.polygon_within(small.points(own[i]), large.points(at[i]))
    return out


def line_meets(small: Shapes, large: Shapes, at: np.ndarray) -> np.ndarray:
    """At least one common point of a path (small) and a closed polygon (large)."""
    touch, _, inside = relate(small, large, at)
    return touch | inside


class Convex:
    """Convex polygons (counter-clockwise) of a batch: corners and the side that leaves each one."""

    def __init__(self, values: np.ndarray, offsets: np.ndarray):
        self.x, self.y, self.off = values[0::2], values[1::2], offsets // 2
        nxt = np.arange(len(self.x)) + 1
        some = np.diff(self.off) > 0
        nxt[self.off[1:][some] - 1] = self.off[:-1][some]
        self.dx, self.dy = self.x[nxt] - self.x, self.y[nxt] - self.y
        turn = np.arctan2(self.dy, self.dx)
        none = (self.dx == 0) & (self.dy == 0)
        turn[none] = turn[nxt[none]]  # a side of length zero goes with the next one
        row = np.repeat(np.arange(len(some)), np.diff(self.off))
        self.by_turn = np.argsort(8 * row + turn, kind="stable")
        self.turns = (8 * row + turn)[self.by_turn]

    @cached_property
    def back(self) -> np.ndarray:
        """Direction of each side's reverse."""
        return np.arctan2(-self.dy, -self.dx)

    @classmethod
    def read(cls, column: pa.Array) -> Convex:
        """From a column of flat coordinates."""
        if isinstance(column, pa.ChunkedArray):
            column = column.combine_chunks()
        size = np.asarray(column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
        return cls(column.flatten().to_numpy(zero_copy_only=False).astype(np.float64), np.concatenate([[0], np.cumsum(size)]))


def _farthest(corners: Convex, row: np.ndarray, back: np.ndarray, dx: np.ndarray, dy: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Greatest position, left of the line through (x, y) along (dx, dy), of a corner of polygon ``row``.

    Sides turn steadily, so the farthest corner begins the first side that
    turns past the line's reverse (``back``); its neighbours are tried too, as
    angles are rounded.
    """
    low, high = corners.off[row], corners.off[row + 1]
    at = np.searchsorted(corners.turns, 8 * row + back)
    top = corners.by_turn[np.where(at < high, at, low)]
    best = np.full(len(row), -np.inf)
    for c in (np.where(top > low, top, high) - 1, top, np.where(top + 1 < high, top + 1, low)):
        best = np.maximum(best, dx * (corners.y[c] - y) - dy * (corners.x[c] - x))
    return best


def _sides(sides: Convex, i: np.ndarray, corners: Convex, j: np.ndarray, least: int):
    """Sides of polygons ``i`` that have ``least`` corners or more, against polygons ``j`` that have any: (pair, side, margin)."""
    n = np.diff(sides.off)[i]
    live = np.flatnonzero((n >= least) & (np.diff(corners.off)[j] > 0))
    for a, b in pieces(n[live], _PAIRS):
        row, k = spread(n[live[a:b]])
        row = live[a:b][row]
        e = sides.off[:-1][i[row]] + k
        yield row, e, 1e-6 * (np.abs(sides.dx[e]) + np.abs(sides.dy[e]) + 1)  # the margin covers rounded corners


def _paired(a: Convex, i: np.ndarray | None, j: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    each = np.arange(len(a.off) - 1)
    return (each if i is None else i), (each if j is None else j)


def convex_apart(a: Convex, b: Convex, i: np.ndarray | None = None, j: np.ndarray | None = None) -> np.ndarray:
    """Per pair (row ``i`` of a, row ``j`` of b, or row by row): some side of one polygon has the other surely beyond it; a segment has two sides."""
    i, j = _paired(a, i, j)
    out = np.zeros(len(i), bool)
    for p, own, q, other in ((a, i, b, j), (b, j, a, i)):
        rest = np.flatnonzero(~out)
        for row, e, margin in _sides(p, own[rest], q, other[rest], 2):
            row = rest[row]
            out[row[_farthest(q, other[row], p.back[e], p.dx[e], p.dy[e], p.x[e], p.y[e]) < -margin]] = True
    return out


def convex_sticks_out(inner: Convex, outer: Convex, i: np.ndarray | None = None, j: np.ndarray | None = None) -> np.ndarray:
    """Per pair: a corner of ``inner`` surely lies outside ``outer``."""
    i, j = _paired(inner, i, j)
    out = np.zeros(len(i), bool)
    for row, e, margin in _sides(outer, j, inner, i, 3):
        out[row[_farthest(inner, i[row], np.arctan2(outer.dy[e], outer.dx[e]), -outer.dx[e], -outer.dy[e], outer.x[e], outer.y[e]) > margin]] = True
    return out


def hulls_settled(small: Shapes, large: Shapes, own: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per pair of hulls (row ``own[i]`` of small, row ``at[i]`` of large): (surely apart, pairs that boxes and corners leave open).

    Corners are integers, so hulls with an inside that are apart have a side
    whose product is one at least: more than ``_sides`` allows for, unless
    that side is about as long as the domain.
    """
    apart = np.zeros(len(own), bool)
    whole = (np.diff(small.off)[own] > 2) & (np.diff(large.off)[at] > 2)
    rest = np.flatnonzero(whole)
    if all(int((s.box[:, 2:] - s.box[:, :2]).sum(1).max(initial=0)) < 900_000 for s in (small, large)):
        apart[rest] = large.strips.beside(small.box[own[rest]], at[rest])
        rest = rest[~apart[rest]]
    return apart, np.concatenate([np.flatnonzero(~whole), rest[_outside(small, own[rest], large, at[rest])]])
