"""Batch kernels that turn polygons into cells and run lists.

A batch holds many objects: ``pts`` (n x 2) with object offsets.  Everything is
exact integer work but for cell areas, whose ties are settled in rationals.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np

from rasterruns.functions import geometry, hilbert
from rasterruns.grid import GridSpec

#: Points x edges compared at once, and boundary cells per pass.
_PAIRS = 4_000_000
CELLS_AT_ONCE = 2_000_000
EDGE, CORE = 1, 2
WEAK, STRONG, FULL = 1, 2, 3


class Batch:
    """Edges of a batch of rings (or open paths) relative to a grid's corner."""

    def __init__(self, pts: np.ndarray, offsets: np.ndarray, grid: GridSpec, closed: bool = True):
        self.grid, self.n = grid, len(offsets) - 1
        self.pts = pts - np.array([grid.x0, grid.y0])
        self.offsets = offsets
        size = np.diff(offsets)
        own = np.repeat(np.arange(self.n), size)
        if closed:
            nxt = np.arange(len(pts)) + 1
            last = offsets[1:][size > 0] - 1
            nxt[last] = offsets[:-1][size > 0]
            self.e, self.obj = np.concatenate([self.pts, self.pts[nxt]], axis=1) if len(pts) else np.zeros((0, 4), np.int64), own
        else:
            keep = np.ones(len(pts), bool)
            keep[offsets[1:][size > 0] - 1] = False
            at = np.flatnonzero(keep)
            alone = offsets[:-1][size == 1]
            self.e = np.concatenate([np.concatenate([self.pts[at], self.pts[at + 1]], 1), np.concatenate([self.pts[alone], self.pts[alone]], 1)]) if len(pts) else np.zeros((0, 4), np.int64)
            self.obj = np.concatenate([own[at], own[alone]])
            order = np.argsort(self.obj, kind="stable")
            self.e, self.obj = self.e[order], self.obj[order]
        self.e_off = np.searchsorted(self.obj, np.arange(self.n + 1))

    def chunks(self):
        """Object ranges whose boundaries take about CELLS_AT_ONCE cells."""
        cost = np.bincount(self.obj, (np.abs(self.e[:, 2] - self.e[:, 0]) + np.abs(self.e[:, 3] - self.e[:, 1])) // self.grid.cell + 2, self.n)
        wide = 2 * self.grid.order + max(1, self.n).bit_length() > 61
        start, total = 0, 0.0
        for i in range(self.n):
            if i > start and (wide or total + cost[i] > CELLS_AT_ONCE):
                yield start, i
                start, total = i, 0.0
            total += cost[i]
        if self.n > start:
            yield start, self.n

    def part(self, a: int, b: int) -> Batch:
        out = object.__new__(Batch)
        out.grid, out.n = self.grid, b - a
        out.pts, out.offsets = self.pts[self.offsets[a] : self.offsets[b]], self.offsets[a : b + 1] - self.offsets[a]
        out.e, out.obj = self.e[self.e_off[a] : self.e_off[b]], self.obj[self.e_off[a] : self.e_off[b]] - a
        out.e_off = self.e_off[a : b + 1] - self.e_off[a]
        return out


def _spread(count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(owner, 0..count-1) of every unit."""
    owner = np.repeat(np.arange(len(count)), count)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)


def _entered(b: Batch) -> tuple[np.ndarray, ...]:
    """Cells that each edge enters, repeats included: (edge, cx, cy, the edges from left to right, which are turned).

    An edge covers, in each column strip, the rows between its heights at the
    strip's ends; cells are half-open, so a right end on the next strip counts there.
    """
    s = b.grid.cell
    flip = b.e[:, 0] > b.e[:, 2]
    e = np.where(flip[:, None], b.e[:, [2, 3, 0, 1]], b.e)
    x0, y0, x1, y1 = e.T
    owner, k = _spread(x1 // s - x0 // s + 1)
    col = (x0 // s)[owner] + k
    x0, y0, x1, y1 = x0[owner], y0[owner], x1[owner], y1[owner]
    dx, dy = x1 - x0, y1 - y0
    q = np.maximum(dx, 1) * s
    left, right = np.maximum(x0, col * s), np.minimum(x1, (col + 1) * s)
    na, nb = y0 * dx + (left - x0) * dy, y0 * dx + (right - x0) * dy
    fa, fb = na // q, nb // q
    excluded = right == (col + 1) * s
    rises, upright = dy >= 0, dx == 0
    low = np.where(rises, fa, fb)
    high = np.where(rises, np.where(excluded, np.maximum(fa, fb - (fb * q == nb)), fb), fa)
    low = np.where(upright, np.minimum(y0, y1) // s, low)
    high = np.where(upright, np.maximum(y0, y1) // s, high)
    strip, j = _spread(high - low + 1)
    return owner[strip], col[strip], low[strip] + j, e, flip


def boundary(b: Batch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells that the edges enter: (object, cx, cy), repeats included."""
    edge, cx, cy, _, _ = _entered(b)
    return b.obj[edge], cx, cy


def _distinct(v: np.ndarray) -> np.ndarray:
    """Sorted values without repeats (np.unique hashes first, which is slower here)."""
    v = np.sort(v)
    return v[np.concatenate([[True], v[1:] != v[:-1]])] if len(v) else v


def edge_ids(b: Batch) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct edge cells: (object, curve id)."""
    o, cx, cy = boundary(b)
    n = b.grid.order
    key = _distinct((o << (2 * n)) | hilbert.encode(cx, cy, n))
    return key >> (2 * n), key & ((1 << (2 * n)) - 1)


def points_inside(o: np.ndarray, px: np.ndarray, py: np.ndarray, b: Batch) -> np.ndarray:
    """Even-odd test of points against the ring of their object."""
    out = np.zeros(len(o), bool)
    size = np.diff(b.e_off)[o]
    at = 0
    cum = np.cumsum(size)
    while at < len(o):
        end = max(at + 1, int(np.searchsorted(cum, (cum[at - 1] if at else 0) + _PAIRS, "right")))
        own, k = _spread(size[at:end])
        e = b.e[b.e_off[o[at:end]][own] + k]
        hit = geometry.crossings(px[at:end][own], py[at:end][own], e)
        out[at:end] = np.bincount(own, hit, end - at).astype(np.int64) % 2 == 1
        at = end
    return out


def _centres(cx: np.ndarray, cy: np.ndarray, s: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Twice the centre coordinates, so that any cell side is exact."""
    return 2 * cx * s + s, 2 * cy * s + s, 2


def _doubled(b: Batch) -> Batch:
    out = b.part(0, b.n)
    out.e = b.e * 2
    return out


def cells_inside(o: np.ndarray, cx: np.ndarray, cy: np.ndarray, b: Batch) -> np.ndarray:
    """Whether cells off the boundary lie inside their object: one centre test each."""
    px, py, _ = _centres(cx, cy, b.grid.cell)
    return points_inside(o, px, py, _doubled(b))


def _offsets(o: np.ndarray, n: int) -> np.ndarray:
    return np.searchsorted(o, np.arange(n + 1))


def _to_lists(o: np.ndarray, start: np.ndarray, end: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    return np.stack([start, end], 1).ravel(), _offsets(o, n) * 2


def runs(o: np.ndarray, ids: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct (object, id) -> maximal runs as a list column."""
    if not len(o):
        return np.zeros(0, np.int64), np.zeros(n + 1, np.int64)
    new = np.concatenate([[True], (o[1:] != o[:-1]) | (ids[1:] != ids[:-1] + 1)])
    head = np.flatnonzero(new)
    last = np.append(head[1:], len(o)) - 1
    return _to_lists(o[head], ids[head], ids[last] + 1, n)


def onestep(b: Batch, neighbours: bool = True) -> dict:
    """Cover and core runs straight from the sorted edge cells.

    Every gap between edge cells along the curve is wholly inside or outside.
    With ``neighbours`` a gap takes the label of the gap that holds a
    neighbour, earlier on the curve, of its first cell; chains of such links
    are followed by pointer jumping, and only the gaps at their ends are tested.
    """
    n = b.grid.order
    po, ph = edge_ids(b)
    m = len(po)
    key = (po << (2 * n)) | ph
    at = np.flatnonzero((po[1:] == po[:-1]) & (ph[1:] > ph[:-1] + 1)) if m else np.zeros(0, np.int64)
    g = len(at)
    go, first = po[at], ph[at] + 1
    cx, cy = hilbert.decode(first, n)
    label = np.zeros(g + 1, bool)  # the last stands for the outside
    parent = np.arange(g + 1)
    if neighbours and g:
        gap_at = np.full(m, -1)
        gap_at[at] = np.arange(g)
        free = np.arange(g)  # gaps without a neighbour so far
        for sx, sy in ((-1, 0), (1, 0), (0, -1), (0, 1)):
            x, y = cx[free] + sx, cy[free] + sy
            ok = (x >= 0) & (y >= 0) & (x < b.grid.side) & (y < b.grid.side)
            mine, ids = free[ok], hilbert.encode(x[ok], y[ok], n)
            early = ids < first[mine] - 1  # the cell just before is an edge cell
            mine, ids = mine[early], ids[early]
            want = (go[mine] << (2 * n)) | ids
            pos = np.searchsorted(key, want, "right") - 1
            known = (pos >= 0) & (po[np.maximum(pos, 0)] == go[mine])
            led = ~(known & (key[np.maximum(pos, 0)] == want))
            parent[mine[led]] = np.where(known, gap_at[np.maximum(pos, 0)], g)[led]
            free = free[parent[free] == free]
        while True:
            up = parent[parent]
            if (up == parent).all():
                break
            parent = up
    roots = np.flatnonzero(parent[:-1] == np.arange(g))
    label[roots] = cells_inside(go[roots], cx[roots], cy[roots], b)
    inside = label[parent[:-1]]
    core = at[inside]
    cut = np.ones(m, bool)
    cut[1:] = (po[1:] != po[:-1]) | (ph[1:] != ph[:-1] + 1)
    cut[core + 1] = False
    head = np.flatnonzero(cut)
    last = np.append(head[1:], m) - 1
    cover = _to_lists(po[head], ph[head], ph[last] + 1, b.n) if m else (np.zeros(0, np.int64), np.zeros(b.n + 1, np.int64))
    return {
        "cover": cover,
        "core": _to_lists(po[core], ph[core] + 1, ph[np.minimum(core + 1, max(m - 1, 0))], b.n),
        "n_edge": np.bincount(po, minlength=b.n),
        "n_gaps": np.bincount(go, minlength=b.n),
        "n_pip": np.bincount(go[roots], minlength=b.n),
    }


def _from_cells(b: Batch, po, ph, co, ch, n_pip=None) -> dict:
    """Run lists from edge and core cells (both sorted and distinct by object)."""
    n = 2 * b.grid.order
    both = _distinct(np.concatenate([(po << n) | ph, (co << n) | ch]))
    zero = np.zeros(b.n, np.int64)
    return {"cover": runs(both >> n, both & ((1 << n) - 1), b.n), "core": runs(co, ch, b.n), "n_edge": np.bincount(po, minlength=b.n), "n_gaps": zero, "n_pip": zero if n_pip is None else n_pip}


def _not_edge(b: Batch, po, ph, o, cx, cy) -> tuple[np.ndarray, np.ndarray]:
    n = 2 * b.grid.order
    key = _distinct((o << n) | hilbert.encode(cx, cy, b.grid.order))
    key = key[~np.isin(key, (po << n) | ph, assume_unique=True)]
    return key >> n, key & ((1 << n) - 1)


def scanline_cells(b: Batch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells between pairs of boundary crossings of each row's centre line: (object, cx, cy)."""
    s = b.grid.cell
    e, obj = b.e, b.obj
    up = e[:, 1] < e[:, 3]
    low = np.where(up[:, None], e, e[:, [2, 3, 0, 1]])
    x0, y0, x1, y1 = low.T
    # rows whose centre line (2 y = 2 row s + s) the edge crosses, half-open
    r0, r1 = -((-(2 * y0 - s)) // (2 * s)), -((-(2 * y1 - s)) // (2 * s))
    own, k = _spread(np.maximum(r1 - r0, 0))
    row = r0[own] + k
    x0, y0, x1, y1 = x0[own], y0[own], x1[own], y1[own]
    top = x0 * 2 * (y1 - y0) + (2 * row * s + s - 2 * y0) * (x1 - x0)  # crossing x times 2 dy
    dy = 2 * (y1 - y0)
    col = (2 * top - s * dy) // (2 * s * dy) + 1  # first column whose centre lies beyond the crossing
    o = obj[own]
    order = np.lexsort((col, row, o))
    o, row, col = o[order], row[order], col[order]
    a, z = col[0::2], col[1::2]
    own, k = _spread(np.maximum(z - a, 0))
    return o[0::2][own], a[own] + k, row[0::2][own]


def scanline(b: Batch) -> dict:
    po, ph = edge_ids(b)
    return _from_cells(b, po, ph, *_not_edge(b, po, ph, *scanline_cells(b)))


def _windows(b: Batch) -> tuple[np.ndarray, ...]:
    """Cell windows of the boxes: first and last column and row by object."""
    s = b.grid.cell
    lo = np.stack([np.minimum.reduceat(b.pts[:, i], b.offsets[:-1]) for i in (0, 1)]) // s
    hi = np.stack([np.maximum.reduceat(b.pts[:, i], b.offsets[:-1]) for i in (0, 1)]) // s
    return lo[0], hi[0], lo[1], hi[1]


def flood(b: Batch) -> dict:
    """Seeds and flooding: one centre test for each connected region of unlabelled cells of the box."""
    po, ph = edge_ids(b)
    ex, ey = hilbert.decode(ph, b.grid.order)
    x0, x1, y0, y1 = _windows(b)
    off = _offsets(po, b.n)
    seeds: list[tuple[int, int, int]] = []
    fields = []
    for i in range(b.n):
        w, h = int(x1[i] - x0[i]) + 1, int(y1[i] - y0[i]) + 1
        field = np.zeros((h, w), np.int64)
        field[ey[off[i] : off[i + 1]] - y0[i], ex[off[i] : off[i + 1]] - x0[i]] = -1
        region = 0
        rows = field.tolist()
        for r in range(h):
            for c in range(w):
                if rows[r][c]:
                    continue
                region += 1
                seeds.append((i, c + int(x0[i]), r + int(y0[i])))
                stack = [(r, c)]
                while stack:  # whole spans at a time
                    y, x = stack.pop()
                    line = rows[y]
                    if line[x]:
                        continue
                    left = x
                    while left and not line[left - 1]:
                        left -= 1
                    right = x
                    while right + 1 < w and not line[right + 1]:
                        right += 1
                    line[left : right + 1] = [region] * (right - left + 1)
                    for ny in (y - 1, y + 1):
                        if 0 <= ny < h:
                            near, k = rows[ny], left
                            while k <= right:
                                if not near[k]:
                                    stack.append((ny, k))
                                    while k <= right and not near[k]:
                                        k += 1
                                k += 1
        fields.append(np.array(rows, np.int64))
    so = np.array([x[0] for x in seeds], np.int64)
    inside = cells_inside(so, np.array([x[1] for x in seeds], np.int64), np.array([x[2] for x in seeds], np.int64), b) if len(seeds) else np.zeros(0, bool)
    start = _offsets(so, b.n)
    co, cx, cy = [], [], []
    for i, field in enumerate(fields):
        good = np.concatenate([[False], inside[start[i] : start[i + 1]], [False]])  # -1 finds the last
        r, c = np.nonzero(good[field])
        co.append(np.full(len(r), i))
        cx.append(c + x0[i])
        cy.append(r + y0[i])
    core = _not_edge(b, po, ph, *(np.concatenate(v).astype(np.int64) for v in (co, cx, cy)))
    return _from_cells(b, po, ph, *core, n_pip=np.bincount(so, minlength=b.n))


def object_grid(b: Batch) -> dict:
    """Every cell of the box by itself: crossed by an edge, else one centre test."""
    po, ph = edge_ids(b)
    x0, x1, y0, y1 = _windows(b)
    w = x1 - x0 + 1
    o, k = _spread(w * (y1 - y0 + 1))
    cx, cy = x0[o] + k % w[o], y0[o] + k // w[o]
    ro, rh = _not_edge(b, po, ph, o, cx, cy)
    rx, ry = hilbert.decode(rh, b.grid.order)
    good = cells_inside(ro, rx, ry, b)
    return _from_cells(b, po, ph, ro[good], rh[good], n_pip=np.bincount(ro, minlength=b.n))


def _clip_exact(ring: list, x0: int, y0: int, s: int) -> Fraction:
    """Area of a ring's part in a cell, in rationals.

    Along each edge's stretch within the cell's rows, the width to its left
    within the cell is integrated over y; only edges that pass the cell's
    columns take more than a product.
    """
    plain, rest = 0, Fraction(0)
    for i, (bx, by) in enumerate(ring):
        ax, ay = ring[i - 1]
        low, high = max(min(ay, by), y0), min(max(ay, by), y0 + s)
        if low >= high or max(ax, bx) <= x0:
            continue
        sign = 1 if by > ay else -1
        if min(ax, bx) >= x0 + s:
            plain += sign * s * (high - low)
            continue
        d = abs(by - ay)
        (px, py), (qx, _) = sorted(((ax, ay), (bx, by)), key=lambda p: p[1])
        # places right of x0 at both ends of the stretch, and the integrals of their clamped values, times d and 2 d^2
        u, v = ((px - x0) * d + (qx - px) * (y - py) for y in (low, high))
        if u == v:
            rest += Fraction(sign * (high - low) * min(max(u, 0), s * d), d)
            continue
        g, h = (0 if w <= 0 else w * w if w <= s * d else s * d * (2 * w - s * d) for w in (u, v))
        rest += Fraction(sign * (high - low) * (h - g), 2 * d * (v - u))
    return abs(plain + rest)


def _settle(b: Batch, o: np.ndarray, col: np.ndarray, row: np.ndarray, share: np.ndarray) -> None:
    """Shares near one half or one, from floating sums, are set by the exact area."""
    s = b.grid.cell
    for i in np.flatnonzero((np.abs(share - 0.5) < 1e-6) | (np.abs(share - 1) < 1e-6)).tolist():
        ring = b.pts[b.offsets[o[i]] : b.offsets[o[i] + 1]].tolist()
        share[i] = float(exact := _clip_exact(ring, int(col[i]) * s, int(row[i]) * s, s) / (s * s))
        share[i] = 0.5 + 1e-9 if exact > Fraction(1, 2) and share[i] == 0.5 else 1 - 1e-9 if exact < 1 and share[i] == 1.0 else share[i]


def coverage(b: Batch, clip_all: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Covered share and 4-way type of all cells that are not empty: (object, id, share, type), sorted.

    Each edge is cut at the grid lines; a piece adds the area to its right
    within its cell and its height to all cells further right in the row.  A
    cell without a piece is full or empty and needs no clipping; ``clip_all``
    gets those from the same sums instead of a fill, which is what a clip of
    every cell costs.
    """
    s, n = b.grid.cell, b.grid.order
    e, obj = b.e.astype(np.float64), b.obj
    cuts_t, cuts_e = [np.zeros(len(e)), np.ones(len(e))], [np.arange(len(e))] * 2
    for i in (0, 1):
        a, z = b.e[:, i], b.e[:, i + 2]
        lo, hi = np.minimum(a, z) // s + 1, -((-np.maximum(a, z)) // s) - 1
        own, k = _spread(np.maximum(hi - lo + 1, 0))
        cuts_t.append(((lo[own] + k) * s - a[own]) / (z[own] - a[own]).astype(np.float64))
        cuts_e.append(own)
    t, own = np.concatenate(cuts_t), np.concatenate(cuts_e)
    order = np.lexsort((t, own))
    t, own = t[order], own[order]
    piece = np.flatnonzero(own[1:] == own[:-1])
    t0, t1, own = t[piece], t[piece + 1], own[piece]
    dx, dy = e[own, 2] - e[own, 0], e[own, 3] - e[own, 1]
    mid = (t0 + t1) / 2
    mx, my, rise = e[own, 0] + mid * dx, e[own, 1] + mid * dy, (t1 - t0) * dy
    cx, cy = np.floor(mx / s).astype(np.int64), np.floor(my / s).astype(np.int64)
    turn = np.bincount(obj, b.e[:, 0] * b.e[:, 3] - b.e[:, 2] * b.e[:, 1], b.n)
    rise = rise * np.where(turn >= 0, -1.0, 1.0)[obj[own]]
    po, ph = edge_ids(b)
    ex, ey = hilbert.decode(ph, n)
    # pieces and edge cells together, by object, row and column
    o = np.concatenate([obj[own], po])
    row, col = np.concatenate([cy, ey]), np.concatenate([cx, ex])
    area = np.concatenate([rise * ((cx + 1) * s - mx), np.zeros(len(po))])
    height = np.concatenate([rise, np.zeros(len(po))])
    order = np.lexsort((col, row, o))
    o, row, col, area, height = (v[order] for v in (o, row, col, area, height))
    new = np.concatenate([[True], (o[1:] != o[:-1]) | (row[1:] != row[:-1]) | (col[1:] != col[:-1])]) if len(o) else np.zeros(0, bool)
    head = np.flatnonzero(new)
    if not len(head):
        z = np.zeros(0, np.int64)
        return z, z, z.astype(float), z
    area, height = np.add.reduceat(area, head), np.add.reduceat(height, head)
    o, row, col = o[head], row[head], col[head]
    line = np.concatenate([[True], (o[1:] != o[:-1]) | (row[1:] != row[:-1])])
    before = np.cumsum(height) - height
    before = before - np.repeat(before[line], np.diff(np.append(np.flatnonzero(line), len(o))))
    share = (area + before * s) / (s * s)
    key = (o << (2 * n)) | hilbert.encode(col, row, n)
    mine = np.isin(key, (po << (2 * n)) | ph)
    o, key, share, row, col, reach = o[mine], key[mine], share[mine], row[mine], col[mine], (before + height)[mine]
    _settle(b, o, col, row, share)
    kind = np.where(share >= 1, FULL, np.where(share > 0.5, STRONG, WEAK))
    if clip_all:
        nxt = np.concatenate([(o[1:] == o[:-1]) & (row[1:] == row[:-1]), [False]])
        gap = np.where(nxt & (reach > s / 2), np.concatenate([col[1:], [0]]) - col - 1, 0)
        own, k = _spread(np.maximum(gap, 0))
        fo, fx, fy = o[own], col[own] + 1 + k, row[own]
        co, ch = fo, hilbert.encode(fx, fy, n)
    else:
        co, ch = _not_edge(b, po, ph, *scanline_cells(b))
    key = np.concatenate([key, (co << (2 * n)) | ch])
    share = np.concatenate([np.clip(share, 0, 1), np.ones(len(co))])
    kind = np.concatenate([kind, np.full(len(co), FULL)])
    order = np.argsort(key)
    key = key[order]
    return key >> (2 * n), key & ((1 << (2 * n)) - 1), share[order], kind[order]


def window_sizes(b: Batch) -> np.ndarray:
    """What ``window_types`` handles for each object: cells of its box, and its edges."""
    x0, x1, y0, y1 = _windows(b)
    return (x1 - x0 + 1) * (y1 - y0 + 1) + np.diff(b.e_off)


def window_types(b: Batch) -> tuple[np.ndarray, ...]:
    """Types of all cells of each object's box, row by row, 0 for empty ones: (x0, y0, width, height, offsets, types).

    The same types as ``coverage`` gives, for boxes of few cells: sums stand at
    their cell's place in its box, so nothing is sorted or looked up.  A cell
    off the boundary is full where the ring winds around it an odd number of times.
    """
    s = b.grid.cell
    x0, x1, y0, y1 = _windows(b)
    w, h = x1 - x0 + 1, y1 - y0 + 1
    off = np.concatenate([[0], np.cumsum(w * h)])
    total = int(off[-1])
    edge, cx, cy, e, flip = _entered(b)
    at = (off[:-1] - y0 * w - x0)[b.obj][edge] + w[b.obj][edge] * cy + cx
    # the stretch of the edge in the cell, as shares of its way from left to right
    d = e[:, 2:] - e[:, :2]
    inverse = 1.0 / np.where(d == 0, 1, d)
    dx, dy = d.T.astype(np.float64)
    px, py = (cx * s - e[edge, 0]).astype(np.float64), (cy * s - e[edge, 1]).astype(np.float64)
    ix, iy = inverse[edge, 0], inverse[edge, 1]
    upright = (d[:, 0] == 0)[edge]
    begin, end = np.where(upright, 0.0, px * ix), np.where(upright, 1.0, (px + s) * ix)
    low, high = py * iy, (py + s) * iy
    begin = np.maximum(np.maximum(begin, np.minimum(low, high)), 0.0)
    end = np.minimum(np.minimum(end, np.maximum(low, high)), 1.0)
    turn = np.bincount(b.obj, b.e[:, 0] * b.e[:, 3] - b.e[:, 2] * b.e[:, 1], b.n)
    rise = np.maximum(end - begin, 0.0) * np.where((turn >= 0)[b.obj] == flip, dy, -dy)[edge]
    area = np.bincount(at, rise * (px + s - (begin + end) * (dx / 2)[edge]), total)
    height = np.bincount(at, rise, total)
    before = np.cumsum(height) - height  # each row adds up to nothing
    kind = (np.rint(before / s).astype(np.int64) & 1).astype(np.uint8) * np.uint8(FULL)
    mine = np.zeros(total, bool)
    mine[at] = True
    mine = np.flatnonzero(mine)
    share = (area[mine] + before[mine] * s) / (s * s)
    close = np.flatnonzero((np.abs(share - 0.5) < 1e-6) | (np.abs(share - 1) < 1e-6))
    if len(close):
        o = np.searchsorted(off, mine[close], "right") - 1
        k = mine[close] - off[o]
        exact = share[close]
        _settle(b, o, x0[o] + k % w[o], y0[o] + k // w[o], exact)
        share[close] = exact
    kind[mine] = np.where(share >= 1, FULL, np.where(share > 0.5, STRONG, WEAK))
    return x0, y0, w, h, off, kind


def from_coverage(b: Batch) -> dict:
    """Run lists from clipped areas, strong and weak cells as edge cells.

    A full cell that the boundary enters is an edge cell here as well
    ("boundary wins"), so all constructions agree.
    """
    o, h, _, _ = coverage(b, clip_all=True)
    n = 2 * b.grid.order
    po, ph = edge_ids(b)
    key = (o << n) | h
    core = key[~np.isin(key, (po << n) | ph)]
    return _from_cells(b, po, ph, core >> n, core & ((1 << n) - 1))


METHODS = {
    "onestep_neighbours": onestep,
    "onestep_pip": lambda b: onestep(b, False),
    "scanline": scanline,
    "flood": flood,
    "clip": from_coverage,
    "object_grid": object_grid,
}
