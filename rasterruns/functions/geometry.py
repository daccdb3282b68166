"""Exact predicates on integer points (NumPy int64; products stay below 2^63 inside the domain)."""

from __future__ import annotations

from fractions import Fraction

import numpy as np


def edges(points: np.ndarray, closed: bool) -> np.ndarray:
    """Rows (x0, y0, x1, y1) of a ring (closed) or a path."""
    if closed:
        return np.concatenate([points, np.roll(points, -1, axis=0)], axis=1)
    return np.concatenate([points[:-1], points[1:]], axis=1)


def crossings(px: np.ndarray, py: np.ndarray, e: np.ndarray) -> np.ndarray:
    """Whether a ray to the right of each point crosses each edge (half-open; broadcasts)."""
    x0, y0, x1, y1 = (e[..., i] for i in range(4))
    side = (x1 - x0) * (py - y0) - (px - x0) * (y1 - y0)
    return ((y0 > py) != (y1 > py)) & ((side > 0) == (y1 > y0)) & (side != 0)


def inside(px: np.ndarray, py: np.ndarray, ring: np.ndarray) -> np.ndarray:
    """Even-odd test of points off the boundary."""
    e = edges(ring, True)
    return crossings(px[:, None], py[:, None], e[None]).sum(axis=1) % 2 == 1


def on_edges(px: np.ndarray, py: np.ndarray, e: np.ndarray) -> np.ndarray:
    """Whether each point lies on some edge."""
    x0, y0, x1, y1 = (e[None, :, i] for i in range(4))
    px, py = px[:, None], py[:, None]
    flat = (x1 - x0) * (py - y0) == (y1 - y0) * (px - x0)
    return (flat & (np.minimum(x0, x1) <= px) & (px <= np.maximum(x0, x1)) & (np.minimum(y0, y1) <= py) & (py <= np.maximum(y0, y1))).any(axis=1)


def covers(points: np.ndarray, ring: np.ndarray) -> np.ndarray:
    """Whether each point lies inside or on the boundary."""
    px, py = points[:, 0], points[:, 1]
    return inside(px, py, ring) | on_edges(px, py, edges(ring, True))


def _turn(ax, ay, bx, by, px, py):
    return np.sign((bx - ax) * (py - ay) - (by - ay) * (px - ax))


def _contact(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For all pairs of edges: (they share a point, they cross in the inside of both)."""
    ax, ay, bx, by = (a[:, None, i] for i in range(4))
    cx, cy, dx, dy = (b[None, :, i] for i in range(4))
    d1, d2 = _turn(ax, ay, bx, by, cx, cy), _turn(ax, ay, bx, by, dx, dy)
    d3, d4 = _turn(cx, cy, dx, dy, ax, ay), _turn(cx, cy, dx, dy, bx, by)
    boxes = (np.maximum(ax, bx) >= np.minimum(cx, dx)) & (np.maximum(cx, dx) >= np.minimum(ax, bx)) & (np.maximum(ay, by) >= np.minimum(cy, dy)) & (np.maximum(cy, dy) >= np.minimum(ay, by))
    touch = boxes & (d1 * d2 <= 0) & (d3 * d4 <= 0)
    return touch, touch & (d1 * d2 < 0) & (d3 * d4 < 0)


def near_edges(e: np.ndarray, box: tuple[int, int, int, int]) -> np.ndarray:
    """Edges whose boxes meet a box."""
    x0, y0, x1, y1 = (e[:, i] for i in range(4))
    return e[(np.maximum(x0, x1) >= box[0]) & (np.minimum(x0, x1) <= box[2]) & (np.maximum(y0, y1) >= box[1]) & (np.minimum(y0, y1) <= box[3])]


def _common(a: np.ndarray, b: np.ndarray) -> tuple[int, int, int, int]:
    lo, hi = np.maximum(a.min(0), b.min(0)), np.minimum(a.max(0), b.max(0))
    return lo[0], lo[1], hi[0], hi[1]


def polygons_intersect(r: np.ndarray, s: np.ndarray) -> bool:
    """At least one common point of two closed simple polygons."""
    box = _common(r, s)
    if box[0] > box[2] or box[1] > box[3]:
        return False
    a, b = near_edges(edges(r, True), box), near_edges(edges(s, True), box)
    if len(a) and len(b) and _contact(a, b)[0].any():
        return True
    return bool(covers(r[:1], s)[0] or covers(s[:1], r)[0])


def line_intersects(path: np.ndarray, ring: np.ndarray) -> bool:
    """At least one common point of a path and a closed polygon."""
    box = _common(path, ring)
    if box[0] > box[2] or box[1] > box[3]:
        return False
    a, b = near_edges(edges(path, False), box), near_edges(edges(ring, True), box)
    if len(a) and len(b) and _contact(a, b)[0].any():
        return True
    return bool(covers(path[:1], ring)[0])


def _covers_exact(px: Fraction, py: Fraction, e: list) -> bool:
    odd = False
    for x0, y0, x1, y1 in e:
        side = (x1 - x0) * (py - y0) - (px - x0) * (y1 - y0)
        if side == 0 and min(x0, x1) <= px <= max(x0, x1) and min(y0, y1) <= py <= max(y0, y1):
            return True
        if (y0 > py) != (y1 > py) and side != 0 and (side > 0) == (y1 > y0):
            odd = not odd
    return odd


def _cuts(a: list[int], b: list[int]) -> list[Fraction]:
    """Places along edge ``a`` (0 to 1) where it meets edge ``b``: one, or both ends of a shared stretch."""
    ax, ay, bx, by = a
    cx, cy, dx, dy = b
    ux, uy, vx, vy = bx - ax, by - ay, dx - cx, dy - cy
    cross = ux * vy - uy * vx
    if cross:
        return [Fraction((cx - ax) * vy - (cy - ay) * vx, cross)]
    length = ux * ux + uy * uy
    return [Fraction((x - ax) * ux + (y - ay) * uy, length) for x, y in ((cx, cy), (dx, dy))] if length else []


def polygon_within(r: np.ndarray, s: np.ndarray) -> bool:
    """Whether every point of simple polygon r lies in closed simple polygon s.

    True iff r's boundary does.  Without contacts the vertices decide; an edge
    in contact with s's boundary is cut there and each piece's midpoint is
    tested in exact rationals.
    """
    if (r.min(0) < s.min(0)).any() or (r.max(0) > s.max(0)).any() or not covers(r, s).all():
        return False
    a = edges(r, True)
    b = near_edges(edges(s, True), (*r.min(0), *r.max(0)))
    if not len(b):
        return True
    touch, cross = _contact(a, b)
    if cross.any():
        return False
    whole = edges(s, True).tolist()
    for i in np.flatnonzero(touch.any(axis=1)).tolist():
        e = a[i].tolist()
        cuts = {Fraction(0), Fraction(1)}
        for j in np.flatnonzero(touch[i]).tolist():
            cuts.update(t for t in _cuts(e, b[j].tolist()) if 0 < t < 1)
        at = sorted(cuts)
        for t0, t1 in zip(at[:-1], at[1:], strict=True):
            t = (t0 + t1) / 2
            if not _covers_exact(e[0] + t * (e[2] - e[0]), e[1] + t * (e[3] - e[1]), whole):
                return False
    return True


def convex_hull(points: np.ndarray) -> np.ndarray:
    """Corners of the hull, counter-clockwise, without collinear ones."""
    p = sorted(set(map(tuple, points.tolist())))
    if len(p) < 3:
        return np.array(p, np.int64)

    def half(seq):
        out: list = []
        for q in seq:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (q[1] - out[-2][1]) <= (out[-1][1] - out[-2][1]) * (q[0] - out[-2][0]):
                out.pop()
            out.append(q)
        return out[:-1]

    return np.array(half(p) + half(p[::-1]), np.int64)


def five_corners(hull: np.ndarray) -> np.ndarray:
    """A convex polygon of at most five corners around a hull: rows of doubles.

    The side whose removal adds the least area goes, where its neighbours'
    lines meet beyond it, until five remain; so every side lies on a hull side.
    """
    p = [tuple(map(float, q)) for q in hull.tolist()]
    if len(p) <= 5:
        return np.array(p, np.float64).reshape(-1, 2)
    lines = [(p[i], (p[(i + 1) % len(p)][0] - p[i][0], p[(i + 1) % len(p)][1] - p[i][1])) for i in range(len(p))]
    corner = list(p)  # corner i: start of side i

    def beyond(i: int):
        """(added area, meeting point) when side i goes."""
        n = len(lines)
        (a, u), (b, v) = lines[i - 1], lines[(i + 1) % n]
        cross = u[0] * v[1] - u[1] * v[0]
        if cross <= 0:
            return None
        t = ((b[0] - a[0]) * v[1] - (b[1] - a[1]) * v[0]) / cross
        q = (a[0] + t * u[0], a[1] + t * u[1])
        c, d = corner[i], corner[(i + 1) % n]
        return abs((c[0] - q[0]) * (d[1] - q[1]) - (c[1] - q[1]) * (d[0] - q[0])) / 2, q

    gain = [beyond(i) for i in range(len(lines))]
    while len(lines) > 5:
        open_ = [i for i, g in enumerate(gain) if g]
        if not open_:
            break
        i = min(open_, key=lambda k: gain[k][0])
        corner[(i + 1) % len(lines)] = gain[i][1]
        del lines[i], corner[i], gain[i]
        n = len(lines)
        for k in (i - 2, i - 1, i, i + 1):
            gain[k % n] = beyond(k % n)
    return np.array(corner, np.float64)


#: Numbers that the batch forms below hold in one table of points.
_TABLE = 2_000_000


def _tables(off: np.ndarray, least: int):
    """Objects of at least ``least`` points in groups of like size: (rows, index of each point, with the last one repeated)."""
    size = np.diff(off)
    order = np.argsort(size, kind="stable")
    order, a = order[np.searchsorted(size[order], least) :], 0
    while a < len(order):
        b = len(order)
        while b > a + 1 and (b - a) * size[order[b - 1]] > _TABLE:
            b = a + (b - a) // 2
        rows = order[a:b]
        yield rows, off[:-1][rows, None] + np.minimum(np.arange(size[rows[-1]]), size[rows, None] - 1)
        a = b


def _halves(x: np.ndarray, y: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of the chain of turns to the left through each row's points, and how many; all rows advance together."""
    n = len(size)
    stack, top, k, live = np.zeros((n, x.shape[1]), np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64), np.arange(n)
    while len(live):
        at = k[live]
        a, b = stack[live, top[live] - 1], stack[live, top[live] - 2]
        ax, ay, bx, by, cx, cy = x[live, a], y[live, a], x[live, b], y[live, b], x[live, at], y[live, at]
        pop = (top[live] > 1) & ((ax - bx) * (cy - by) <= (ay - by) * (cx - bx))
        top[live[pop]] -= 1
        push = live[~pop]
        stack[push, top[push]] = at[~pop]
        top[push] += 1
        k[push] += 1
        live = live[k[live] < size[live]]
    return stack, top


def convex_hulls(pts: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``convex_hull`` of each object, as points and offsets."""
    row = np.repeat(np.arange(len(off) - 1), np.diff(off))
    pts = pts[np.lexsort((pts[:, 1], pts[:, 0], row))]
    new = np.concatenate([[True], (row[1:] != row[:-1]) | (pts[1:] != pts[:-1]).any(1)])[: len(pts)]
    pts, off = pts[new], np.concatenate([[0], np.cumsum(np.bincount(row[new], minlength=len(off) - 1))])
    few = np.flatnonzero(np.repeat(np.diff(off) < 2, np.diff(off)))
    found = [(row[new][few], np.zeros(len(few), np.int64), few)]
    for rows, at in _tables(off, 2):
        x, y, size = pts[at, 0], pts[at, 1], np.diff(off)[rows]
        back = np.maximum(size[:, None] - 1 - np.arange(x.shape[1]), 0)
        for part, turn in enumerate((None, back)):
            u, v = (x, y) if turn is None else (np.take_along_axis(c, turn, 1) for c in (x, y))
            stack, top = _halves(u, v, size)
            i, k = np.nonzero(np.arange(x.shape[1]) < top[:, None] - 1)
            place = stack[i, k] if turn is None else turn[i, stack[i, k]]
            found.append((rows[i], part * (pts.shape[0] + 1) + k, at[i, place]))
    row, rank, e = (np.concatenate(c) for c in zip(*found, strict=True))
    order = np.lexsort((rank, row))
    return pts[e[order]], np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(off) - 1))])


def all_five_corners(hulls: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``five_corners`` of each hull, as points and offsets: every round takes one side off each hull that has more than five."""
    size = np.diff(off)
    few = np.flatnonzero(np.repeat(size <= 5, size))
    found = [(np.repeat(np.arange(len(size)), size)[few], few - np.repeat(off[:-1], size)[few], hulls[few].astype(np.float64))]
    for rows, at in _tables(off, 6):
        n, m = len(rows), at.shape[1]
        left = size[rows].copy()
        here = np.arange(m) < left[:, None]
        corner = hulls[at].astype(np.float64)
        after, before = (np.arange(m) + 1) % left[:, None], (np.arange(m) - 1) % left[:, None]
        start, way = corner.copy(), np.take_along_axis(corner, after[:, :, None], 1) - corner
        gain, meet = np.full((n, m), np.inf), np.zeros((n, m, 2))

        def beyond(i: np.ndarray, k: np.ndarray):
            """Added area and meeting point when side k of row i goes; none where the neighbours don't meet."""
            p, q = before[i, k], after[i, k]
            (ax, ay), (ux, uy), (bx, by), (vx, vy) = start[i, p].T, way[i, p].T, start[i, q].T, way[i, q].T
            cross = ux * vy - uy * vx
            with np.errstate(divide="ignore", invalid="ignore"):
                t = ((bx - ax) * vy - (by - ay) * vx) / cross
                x, y = ax + t * ux, ay + t * uy
                (cx, cy), (dx, dy) = corner[i, k].T, corner[i, q].T
                area = np.abs((cx - x) * (dy - y) - (cy - y) * (dx - x)) / 2
            gain[i, k] = np.where(cross <= 0, np.inf, area)
            meet[i, k] = np.stack([x, y], 1)

        beyond(*np.nonzero(here))
        live = np.arange(n)
        while len(live):
            k = gain[live].argmin(1)
            some = np.isfinite(gain[live, k])
            live, k = live[some], k[some]
            p, q = before[live, k], after[live, k]
            corner[live, q] = meet[live, k]
            here[live, k], gain[live, k] = False, np.inf
            after[live, p], before[live, q] = q, p
            left[live] -= 1
            for side in (p, q):
                beyond(live, side)
            live = live[left[live] > 5]
        i, k = np.nonzero(here)
        found.append((rows[i], k, corner[i, k]))
    row, rank, values = (np.concatenate(c) for c in zip(*found, strict=True))
    order = np.lexsort((rank, row))
    return values[order], np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(size)))])


def convex_apart(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether some side of a convex polygon (counter-clockwise) has the other strictly beyond it; a segment has two sides.

    A margin keeps rounded corners on the safe side: never true for polygons that touch.
    """
    for p, q in ((a, b), (b, a)):
        if len(p) < 2:
            continue
        d = np.roll(p, -1, axis=0) - p
        side = d[:, None, 0] * (q[None, :, 1] - p[:, None, 1]) - d[:, None, 1] * (q[None, :, 0] - p[:, None, 0])
        margin = 1e-6 * (np.abs(d).sum(axis=1) + 1)
        if (side.max(axis=1) < -margin).any():
            return True
    return False


def convex_sticks_out(inner: np.ndarray, outer: np.ndarray) -> bool:
    """Whether a corner of ``inner`` surely lies outside convex ``outer``."""
    if len(outer) < 3:
        return False
    d = np.roll(outer, -1, axis=0) - outer
    side = d[:, None, 0] * (inner[None, :, 1] - outer[:, None, 1]) - d[:, None, 1] * (inner[None, :, 0] - outer[:, None, 0])
    return bool((side.min(axis=1) < -1e-6 * (np.abs(d).sum(axis=1) + 1)).any())


def is_simple(ring: np.ndarray) -> bool:
    """No two sides share a point but neighbours their corner; no side of length zero."""
    n = len(ring)
    e = edges(ring, True)
    if n < 3 or ((e[:, 0] == e[:, 2]) & (e[:, 1] == e[:, 3])).any():
        return False
    for a in range(0, n, 512):
        touch, cross = _contact(e[a : a + 512], e)
        i, j = np.nonzero(touch)
        i += a
        far = (i != j) & ((i + 1) % n != j) & ((j + 1) % n != i)
        if far.any() or cross.any():
            return False
    nxt = np.roll(ring, -2, axis=0)
    u, v = e[:, 2:] - e[:, :2], nxt - e[:, 2:]
    flat = (u[:, 0] * v[:, 1] == u[:, 1] * v[:, 0]) & ((u * v).sum(axis=1) < 0)
    return not flat.any()  # no spike that folds back on itself
