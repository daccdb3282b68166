"""Building blocks of the DuckDB oracles: cells, labels and exact predicates from the vertices, without any curve code."""

from __future__ import annotations

from rasterruns.functions.hilbert import duckdb_ids
from rasterruns.grid import DOMAIN, DOMAIN_BITS
from rasterruns.sources.layers import duckdb_layer


def edges(name: str, closed: bool = True) -> str:
    """CTE ``{name}_e(oid, x0, y0, x1, y1)``."""
    if closed:
        return f"""{name}_e AS (SELECT oid, x AS x0, y AS y0, coalesce(lead(x) OVER w, first_value(x) OVER w) AS x1, coalesce(lead(y) OVER w, first_value(y) OVER w) AS y1
FROM {name}_v WINDOW w AS (PARTITION BY oid ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING))"""
    return f"""{name}_l AS (SELECT oid, x AS x0, y AS y0, lead(x) OVER w AS x1, lead(y) OVER w AS y1 FROM {name}_v WINDOW w AS (PARTITION BY oid ORDER BY i)),
{name}_e AS (SELECT * FROM {name}_l WHERE x1 IS NOT NULL)"""


def side_of(name: str, order: int | None = None, max_cells: int = 750) -> str:
    """CTE ``{name}_s(oid, s, k)``: each object's cell side, one for all or that of its private grid."""
    if order is not None:
        return f"{name}_s AS (SELECT oid, {1 << (DOMAIN_BITS - order)}::BIGINT AS s, {DOMAIN_BITS - order} AS k FROM {name})"
    return f"""{name}_s AS (SELECT oid, 1::BIGINT << k AS s, k FROM (SELECT oid, min(k) AS k FROM {name}, (SELECT unnest(range(22)) AS k)
  WHERE (xmax // (1::BIGINT << k) - xmin // (1::BIGINT << k) + 1) * (ymax // (1::BIGINT << k) - ymin // (1::BIGINT << k) + 1) <= {max_cells} GROUP BY oid))"""


def cells(name: str, order: int | None, closed: bool = True, max_cells: int = 750, sides: str | None = None) -> str:
    """CTEs ``{name}_edge`` and, for polygons, ``{name}_core`` and ``{name}_cells`` (oid, cx, cy, core).

    A core cell's centre has an odd number of edges to its right; the edges are
    first spread over the rows whose centre line they cross.
    """
    sides = side_of(name, order, max_cells) + ", " if sides is None else sides  # "": the layer brings {name}_s
    out = f"""{edges(name, closed)}, {sides}
{name}_d AS (SELECT oid, s, CASE WHEN x0 <= x1 THEN x0 ELSE x1 END AS xa, CASE WHEN x0 <= x1 THEN y0 ELSE y1 END AS ya, CASE WHEN x0 <= x1 THEN x1 ELSE x0 END AS xb, CASE WHEN x0 <= x1 THEN y1 ELSE y0 END AS yb FROM {name}_e JOIN {name}_s USING (oid)),
{name}_c1 AS (SELECT *, unnest(range(xa // s, xb // s + 1)) AS c FROM {name}_d),
{name}_c2 AS (SELECT oid, c, s, xa, ya, xb, yb, xb - xa AS dx, yb - ya AS dy, greatest(xb - xa, 1) * s AS q, least(xb, (c + 1) * s) AS r, ya * (xb - xa) + (greatest(xa, c * s) - xa) * (yb - ya) AS na, ya * (xb - xa) + (least(xb, (c + 1) * s) - xa) * (yb - ya) AS nb FROM {name}_c1),
{name}_c3 AS (SELECT oid, c,
  CASE WHEN dx = 0 THEN least(ya, yb) // s WHEN dy >= 0 THEN na // q ELSE nb // q END AS lo,
  CASE WHEN dx = 0 THEN greatest(ya, yb) // s WHEN dy < 0 THEN na // q WHEN r < (c + 1) * s THEN nb // q ELSE greatest(na // q, (nb - 1) // q) END AS hi FROM {name}_c2),
{name}_edge AS MATERIALIZED (SELECT DISTINCT oid, c AS cx, cy FROM (SELECT oid, c, unnest(range(lo, hi + 1)) AS cy FROM {name}_c3))"""
    if not closed:
        return out
    return f"""{out},
{name}_w1 AS (SELECT oid, s, ymin, ymax, unnest(range(xmin // s, xmax // s + 1)) AS cx FROM {name} JOIN {name}_s USING (oid)),
{name}_w2 AS (SELECT oid, s, cx, unnest(range(ymin // s, ymax // s + 1)) AS cy FROM {name}_w1),
{name}_x1 AS (SELECT oid, s, x0, y0, x1, y1, unnest(range(greatest(least(y0, y1) // s - 1, 0), greatest(y0, y1) // s + 2)) AS cy FROM {name}_e JOIN {name}_s USING (oid)),
{name}_x AS (SELECT * FROM {name}_x1 WHERE (2 * y0 > (2 * cy + 1) * s) <> (2 * y1 > (2 * cy + 1) * s)),
{name}_core AS MATERIALIZED (SELECT w.oid, w.cx, w.cy FROM ({name}_w2 w ANTI JOIN {name}_edge USING (oid, cx, cy)) w JOIN {name}_x e ON e.oid = w.oid AND e.cy = w.cy
  WHERE ((x1 - x0) * ((2 * w.cy + 1) * w.s - 2 * y0) - ((2 * w.cx + 1) * w.s - 2 * x0) * (y1 - y0) > 0) = (y1 > y0)
  GROUP BY ALL HAVING count(*) % 2 = 1),
{name}_cells AS (SELECT oid, cx, cy, 0 AS core FROM {name}_edge UNION ALL SELECT oid, cx, cy, 1 FROM {name}_core)"""


def types(name: str) -> str:
    """CTE ``{name}_types(oid, cx, cy, type)`` after ``cells``: 1 weak, 2 strong, 3 full.

    The covered area of an edge cell is the line integral of the abscissa,
    held within the cell, over the boundary's heights within the cell's row.
    A touched cell is full if no edge enters its open inside, which integers decide.
    """
    held = "CASE WHEN {0} <= 0 THEN 0 WHEN {0} >= s THEN s * s / 2.0 + s * ({0} - s) ELSE {0} * {0} / 2 END"
    return f"""{name}_a1 AS (SELECT c.oid, c.cx, c.cy, s, x0 - c.cx * s AS px, y0, x1 - x0 AS dx, y1 - y0 AS dy, greatest(least(y0, (c.cy + 1) * s), c.cy * s) AS ya, greatest(least(y1, (c.cy + 1) * s), c.cy * s) AS yb
  FROM {name}_edge c JOIN {name}_s USING (oid) JOIN {name}_e e ON e.oid = c.oid AND least(y0, y1) < (c.cy + 1) * s AND greatest(y0, y1) > c.cy * s),
{name}_a2 AS (SELECT oid, cx, cy, s, yb - ya AS rise, px + (ya - y0) * dx / dy::DOUBLE AS xa, px + (yb - y0) * dx / dy::DOUBLE AS xb FROM {name}_a1),
{name}_a3 AS (SELECT oid, cx, cy, abs(sum(rise * CASE WHEN xa <= 0 AND xb <= 0 THEN 0 WHEN xa >= s AND xb >= s THEN s WHEN xa BETWEEN 0 AND s AND xb BETWEEN 0 AND s THEN (xa + xb) / 2
  ELSE ({held.format('xb')} - {held.format('xa')}) / (xb - xa) END)) / any_value(s * s) AS share FROM {name}_a2 GROUP BY oid, cx, cy),
{name}_a4 AS (SELECT c.oid, c.cx, c.cy, x0, y0, x1, y1, c.cx * s AS qx, c.cy * s AS qy, s, (x1 - x0) * (c.cy * s - y0) - (y1 - y0) * (c.cx * s - x0) AS t, (y1 - y0) * s AS tx, (x1 - x0) * s AS ty
  FROM {name}_a3 c JOIN {name}_s USING (oid) JOIN {name}_e e ON e.oid = c.oid AND least(x0, x1) < (c.cx + 1) * s AND greatest(x0, x1) > c.cx * s AND least(y0, y1) < (c.cy + 1) * s AND greatest(y0, y1) > c.cy * s WHERE share > 0.99),
{name}_a5 AS (SELECT DISTINCT oid, cx, cy FROM {name}_a4 WHERE greatest(t, t - tx, t + ty, t - tx + ty) > 0 AND least(t, t - tx, t + ty, t - tx + ty) < 0),
{name}_types AS MATERIALIZED (SELECT c.oid, c.cx, c.cy, CASE WHEN share > 0.99 AND e.oid IS NULL THEN 3 WHEN share > 0.5 + 1e-9 THEN 2 ELSE 1 END AS type
  FROM {name}_edge c LEFT JOIN {name}_a3 a ON a.oid = c.oid AND a.cx = c.cx AND a.cy = c.cy LEFT JOIN {name}_a5 e ON e.oid = c.oid AND e.cx = c.cx AND e.cy = c.cy UNION ALL SELECT oid, cx, cy, 3 FROM {name}_core)"""


def hulls(name: str) -> str:
    """CTEs ``{name}_hull(oid, x, y)`` (corners) and ``{name}_side(oid, x, y, dx, dy)``, counter-clockwise.

    A point is a corner where the directions to all others leave a gap of more than half a turn.
    """
    return f"""{name}_hp AS (SELECT DISTINCT oid, x, y FROM {name}_v SEMI JOIN {name} USING (oid)),
{name}_g AS (SELECT a.oid, a.x, a.y, atan2(b.y - a.y, b.x - a.x) AS t FROM {name}_hp a LEFT JOIN {name}_hp b ON a.oid = b.oid AND (a.x <> b.x OR a.y <> b.y)),
{name}_g2 AS (SELECT *, lead(t) OVER (PARTITION BY oid, x, y ORDER BY t) - t AS gap FROM {name}_g),
{name}_hull AS MATERIALIZED (SELECT oid, x, y FROM {name}_g2 GROUP BY ALL HAVING max(t) IS NULL OR greatest(coalesce(max(gap), 0), min(t) + 2 * pi() - max(t)) > pi() + 1e-11),
{name}_mid AS (SELECT oid, avg(x) AS mx, avg(y) AS my FROM {name}_hull GROUP BY oid),
{name}_side AS MATERIALIZED (SELECT oid, x, y, coalesce(lead(x) OVER w, first_value(x) OVER w) - x AS dx, coalesce(lead(y) OVER w, first_value(y) OVER w) - y AS dy FROM {name}_hull JOIN {name}_mid USING (oid)
  WINDOW w AS (PARTITION BY oid ORDER BY atan2(y - my, x - mx) ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING))"""


def candidates(r: str, s: str, within: bool = False) -> str:
    """CTE ``cand(rid, sid)``."""
    test = "r.xmin >= s.xmin AND r.xmax <= s.xmax AND r.ymin >= s.ymin AND r.ymax <= s.ymax" if within else "r.xmin <= s.xmax AND s.xmin <= r.xmax AND r.ymin <= s.ymax AND s.ymin <= r.ymax"
    return f"cand AS (SELECT r.oid AS rid, s.oid AS sid FROM {r} r JOIN {s} s ON {test})"


#: Layers by the size of their objects: the cells of the smaller ones are joined to the candidates first.
_BY_SIZE = ("tracks", "ponds", "lakes", "sites", "parks", "zones", "probes", "counties", "provinces")


def _meeting(r: str, s: str, table: str, columns: str, keep: str = "", on: str = "") -> str:
    """CTE ``met``: a row for each candidate with a common cell, by aggregates over the rows a (of r) and b (of s) of ``{layer}_{table}``."""
    rank = lambda x: next((i for i, n in enumerate(_BY_SIZE) if n in x), 0)
    first, mine, then, other = (r, "rid", s, "sid") if rank(r) < rank(s) else (s, "sid", r, "rid")
    a, b = ("f", "o") if first == r else ("o", "f")
    return f"""first_ AS MATERIALIZED (SELECT rid, sid, c.* EXCLUDE (oid) FROM cand JOIN {first}_{table} c ON c.oid = {mine}),
met AS (SELECT rid, sid, {columns.replace('a.', a + '.').replace('b.', b + '.')} FROM first_ f JOIN {then}_{table} o ON o.oid = f.{other} AND o.cx = f.cx AND o.cy = f.cy {keep} GROUP BY rid, sid)"""


def shared(r: str, s: str) -> str:
    """CTE ``met(rid, sid, sure, r_core, s_core)``: pairs with a common cell, and whether one is core on a side."""
    return _meeting(r, s, "cells", "max(greatest(a.core, b.core)) AS sure, max(a.core) AS r_core, max(b.core) AS s_core")


VERDICT = "CASE WHEN sure IS NULL THEN 'miss' WHEN sure = 1 THEN 'hit' ELSE 'unsure' END"


def merges(order: str) -> str:
    """How many merges an order takes, from which of the three find a common cell."""
    out, n = "", 0
    for step in order.split(","):
        n += 1
        out += f" WHEN {dict(CC='sure IS NULL', CK='s_core = 1', KC='r_core = 1')[step]} THEN {n}"
    return f"CASE{out} ELSE {n} END"


def _layers(r: str, s: str, only: int | None = None) -> str:
    return f"WITH RECURSIVE {duckdb_layer(r, only)}, {duckdb_layer(s, only)}"


def dual_verdicts(r: str, s: str, order: int, within: bool = False, only: int | None = None, merge_order: str = "CC,CK,KC") -> str:
    """``WITH`` text up to CTE ``verdicts(rid, sid, verdict, merges)``."""
    return f"{_layers(r, s, only)}, {cells(r, order)}, {cells(s, order)}, {candidates(r, s, within)}, {shared(r, s)}, verdicts AS (SELECT rid, sid, {VERDICT} AS verdict, {merges(merge_order)} AS merges FROM cand LEFT JOIN met USING (rid, sid))"


def mixed_verdicts(r: str, s: str, order_r: int, order_s: int) -> str:
    """The finer side's cells, scaled down, against the coarser side's cells: only the latter's core proves a hit."""
    low, fine = min(order_r, order_s), r if order_r > order_s else s
    d = abs(order_r - order_s)
    own = "s_core" if fine == r else "r_core"
    scaled = f"{fine}_cells_ AS (SELECT DISTINCT oid, cx >> {d} AS cx, cy >> {d} AS cy, 0 AS core FROM {fine}_cells)" if d else f"{fine}_cells_ AS (SELECT * FROM {fine}_cells)"
    met = shared(r, s).replace(f"{fine}_cells", f"{fine}_cells_")
    steps = "CC,CK,KC" if not d else "CC,CK" if fine == r else "CC,KC"
    verdict = VERDICT if not d else VERDICT.replace("sure = 1", f"{own} = 1")
    return f"{_layers(r, s)}, {cells(r, order_r)}, {cells(s, order_s)}, {candidates(r, s)}, {scaled}, {met}, verdicts AS (SELECT rid, sid, {verdict} AS verdict, {merges(steps)} AS merges FROM cand LEFT JOIN met USING (rid, sid))"


def within_verdicts(r: str, s: str, order: int, strict: bool = False, within: bool = True) -> str:
    miss = "WHEN n_out > 0 THEN 'miss'" if strict else ""
    return f"""{_layers(r, s)}, {cells(r, order)}, {cells(s, order)}, {candidates(r, s, within)},
mine AS MATERIALIZED (SELECT rid, sid, a.cx, a.cy FROM cand JOIN {r}_cells a ON a.oid = rid),
held AS (SELECT rid, sid, count(*) AS n, count(b.oid) AS n_in, count(*) - count(b.oid) AS n_out, coalesce(sum(b.core), 0) AS n_core FROM mine a LEFT JOIN {s}_cells b ON b.oid = sid AND a.cx = b.cx AND a.cy = b.cy GROUP BY rid, sid),
verdicts AS (SELECT rid, sid, CASE WHEN n_in = 0 THEN 'miss' {miss} WHEN n_core = n THEN 'hit' ELSE 'unsure' END AS verdict, 0 AS merges FROM held)"""


def line_verdicts(r: str, s: str, order: int) -> str:
    return f"""{_layers(r, s)}, {cells(r, order)}, {cells(s, order, False)}, {candidates(r, s)},
mine AS MATERIALIZED (SELECT rid, sid, b.cx, b.cy FROM cand JOIN {s}_edge b ON b.oid = sid),
met AS (SELECT rid, sid, max(a.core) AS sure FROM mine b JOIN {r}_cells a ON a.oid = rid AND a.cx = b.cx AND a.cy = b.cy GROUP BY rid, sid),
verdicts AS (SELECT rid, sid, {VERDICT} AS verdict, 0 AS merges FROM cand LEFT JOIN met USING (rid, sid))"""


#: Two common cells prove an intersection if one is full or both are strong.
_SURE = "a.type = 3 OR b.type = 3 OR (a.type = 2 AND b.type = 2)"


def coded_verdicts(r: str, s: str, order: int, only: int | None = None) -> str:
    """The coded filter from the cells' types."""
    met = _meeting(r, s, "types", f"max(CASE WHEN {_SURE} THEN 1 ELSE 0 END) AS sure")
    return f"{_layers(r, s, only)}, {cells(r, order)}, {types(r)}, {cells(s, order)}, {types(s)}, {candidates(r, s)}, {met}, verdicts AS (SELECT rid, sid, {VERDICT} AS verdict, 0 AS merges FROM cand LEFT JOIN met USING (rid, sid))"


def coded_within_verdicts(r: str, s: str, order: int, within: bool = True) -> str:
    """A cell of r outside s, full in r only, or strong in r and weak in s: miss; all full in s: hit."""
    return f"""{_layers(r, s)}, {cells(r, order)}, {types(r)}, {cells(s, order)}, {types(s)}, {candidates(r, s, within)},
mine AS MATERIALIZED (SELECT rid, sid, a.cx, a.cy, a.type FROM cand JOIN {r}_types a ON a.oid = rid),
held AS (SELECT rid, sid, bool_or(b.type IS NULL OR (a.type = 3 AND b.type <> 3) OR (a.type = 2 AND b.type = 1)) AS bad, bool_and(b.type IS NOT NULL AND b.type = 3) AS good FROM mine a LEFT JOIN {s}_types b ON b.oid = sid AND a.cx = b.cx AND a.cy = b.cy GROUP BY rid, sid),
verdicts AS (SELECT rid, sid, CASE WHEN bad THEN 'miss' WHEN good THEN 'hit' ELSE 'unsure' END AS verdict, 0 AS merges FROM held)"""


def upscaled(source: str, levels: str, keys: str) -> str:
    """Types at a coarser level: all children full; a proven share above one half; else weak."""
    return f"""SELECT {keys}, cx >> {levels} AS cx, cy >> {levels} AS cy, CASE WHEN count(*) FILTER (WHERE type = 3) = 1 << (2 * any_value({levels})) THEN 3
  WHEN 2 * count(*) FILTER (WHERE type = 3) + count(*) FILTER (WHERE type = 2) > 1 << (2 * any_value({levels})) OR (2 * count(*) FILTER (WHERE type = 3) + count(*) FILTER (WHERE type = 2) = 1 << (2 * any_value({levels})) AND count(*) FILTER (WHERE type = 2) > 0) THEN 2 ELSE 1 END AS type
  FROM {source} GROUP BY {keys}, cx >> {levels}, cy >> {levels}"""


def raster_verdicts(r: str, s: str, predicate: str = "intersects", within: bool = False, max_cells: int = 750, only: int | None = None) -> str:
    """The local-raster filters: both sides on the coarser of the pair's private grids."""
    up = "".join(
        f"""{x}_want AS (SELECT DISTINCT {i} AS oid, top, top - c.k AS d FROM tops JOIN {x}_s c ON c.oid = {i}),
{x}_at AS (SELECT oid, top, d, t.cx, t.cy, t.type FROM {x}_want JOIN {x}_types t USING (oid)),
{x}_up AS MATERIALIZED ({upscaled(f'{x}_at', 'd', 'oid, top')}),
"""
        for x, i in ((r, "rid"), (s, "sid"))
    )
    head = f"""{_layers(r, s, only)}, {cells(r, None, max_cells=max_cells)}, {types(r)}, {cells(s, None, max_cells=max_cells)}, {types(s)}, {candidates(r, s, within)},
tops AS (SELECT rid, sid, greatest(a.k, b.k) AS top, greatest(a.k, b.k) > b.k AS scaled FROM cand JOIN {r}_s a ON a.oid = rid JOIN {s}_s b ON b.oid = sid),
{up}mine AS MATERIALIZED (SELECT rid, sid, scaled, tops.top AS top, a.cx, a.cy, a.type FROM tops JOIN {r}_up a ON a.oid = rid AND a.top = tops.top)"""
    if predicate == "intersects":
        return f"""{head}, met AS (SELECT rid, sid, max(CASE WHEN {_SURE} THEN 1 ELSE 0 END) AS sure FROM mine a JOIN {s}_up b ON b.oid = sid AND b.top = a.top AND a.cx = b.cx AND a.cy = b.cy GROUP BY rid, sid),
verdicts AS (SELECT rid, sid, {VERDICT} AS verdict, 0 AS merges FROM cand LEFT JOIN met USING (rid, sid))"""
    return f"""{head}, held AS (SELECT rid, sid, bool_or(b.type IS NULL OR (a.type = 3 AND b.type <> 3) OR (a.type = 2 AND b.type = 1 AND NOT scaled)) AS bad, bool_and(b.type IS NOT NULL AND b.type = 3) AS good FROM mine a LEFT JOIN {s}_up b ON b.oid = sid AND b.top = a.top AND a.cx = b.cx AND a.cy = b.cy GROUP BY rid, sid),
verdicts AS (SELECT rid, sid, CASE WHEN bad THEN 'miss' WHEN good THEN 'hit' ELSE 'unsure' END AS verdict, 0 AS merges FROM held)"""


def hull_verdicts(r: str, s: str, predicate: str = "intersects", within: bool = False, only: int | None = None) -> str:
    """The corner and hull filters: what five corners settle, the hulls within them settle as well."""
    if predicate == "within":
        out = f"""out_ AS (SELECT DISTINCT rid, sid FROM cand JOIN {r}_hull a ON a.oid = rid JOIN {s}_side b ON b.oid = sid WHERE b.dx * (a.y - b.y) - b.dy * (a.x - b.x) < 0
  AND sid IN (SELECT oid FROM {s}_hull GROUP BY oid HAVING count(*) > 2))"""
    else:
        apart = lambda one, i, two, j: f"SELECT rid, sid FROM (SELECT rid, sid FROM cand JOIN {one}_side a ON a.oid = {i} JOIN {two}_hull b ON b.oid = {j} WHERE a.dx <> 0 OR a.dy <> 0 GROUP BY rid, sid, a.x, a.y HAVING max(a.dx * (b.y - a.y) - a.dy * (b.x - a.x)) < 0)"
        out = f"out_ AS (SELECT DISTINCT * FROM ({apart(r, 'rid', s, 'sid')} UNION ALL {apart(s, 'sid', r, 'rid')}))"
    return f"{_layers(r, s, only)}, {hulls(r)}, {hulls(s)}, {candidates(r, s, within)}, {out}, verdicts AS (SELECT rid, sid, CASE WHEN o.rid IS NULL THEN 'unsure' ELSE 'miss' END AS verdict, 0 AS merges FROM cand LEFT JOIN out_ o USING (rid, sid))"


def direct_verdicts(r: str, s: str, within: bool = False, only: int | None = None) -> str:
    return f"{_layers(r, s, only)}, {candidates(r, s, within)}, verdicts AS (SELECT rid, sid, 'unsure' AS verdict, 0 AS merges FROM cand)"


def method_verdicts(r: str, s: str, method: str, order: int, predicate: str = "intersects", boxes: str = "intersects", max_cells: int = 750, only: int | None = None) -> str:
    """``WITH`` text up to CTE ``verdicts`` of any method and predicate."""
    inner = boxes == "within"
    if method == "direct":
        return direct_verdicts(r, s, inner, only)
    if method == "corner_hull":
        return hull_verdicts(r, s, predicate, inner, only)
    if method == "local_raster":
        return raster_verdicts(r, s, predicate, inner, max_cells, only)
    if predicate == "line":
        return line_verdicts(r, s, order)
    if predicate == "within":
        return (coded_within_verdicts if method == "coded" else within_verdicts)(r, s, order, within=inner)
    return coded_verdicts(r, s, order, only) if method == "coded" else dual_verdicts(r, s, order, inner, only)


def shares(verdicts: str, **labels) -> str:
    """Counts, merges and shares by verdict under labels, as one SELECT."""
    names = ", ".join(f"{v!r} AS {k}" if isinstance(v, str) else f"{v} AS {k}" for k, v in labels.items())
    return f"SELECT {names}{', ' if names else ''}* FROM ({verdicts} SELECT verdict, count(*) AS n, CAST(sum(merges) AS BIGINT) AS merges, count(*) * 10000 // (SELECT count(*) FROM verdicts) AS share FROM verdicts GROUP BY verdict)"


def _sides(a: str, b: str) -> str:
    turn = lambda p, q, x: f"sign(({p}.x1 - {p}.x0) * ({q}.y{x} - {p}.y0) - ({p}.y1 - {p}.y0) * ({q}.x{x} - {p}.x0))"
    return f"{turn(a, b, 0)} * {turn(a, b, 1)} AS d1, {turn(b, a, 0)} * {turn(b, a, 1)} AS d2"


_BOXES = "greatest(a.x0, a.x1) >= least(b.x0, b.x1) AND greatest(b.x0, b.x1) >= least(a.x0, a.x1) AND greatest(a.y0, a.y1) >= least(b.y0, b.y1) AND greatest(b.y0, b.y1) >= least(a.y0, a.y1)"


def _inside(point: str, ring: str, pid: str, rid: str, name: str) -> str:
    """CTE of pairs whose point (px, py) lies strictly inside the ring by parity."""
    return f"{name} AS (SELECT rid, sid FROM {point} JOIN {ring}_e e ON e.oid = {rid} WHERE (y0 > py) <> (y1 > py) AND ((x1 - x0) * (py - y0) - (px - x0) * (y1 - y0) > 0) = (y1 > y0) GROUP BY ALL HAVING count(*) % 2 = 1)"


def exact_intersects(r: str, s: str, line: bool = False) -> str:
    """``WITH`` text up to CTE ``result(rid, sid)``; ``line``: s is a path layer."""
    more = "" if line else f", pr AS (SELECT rid, sid, x AS px, y AS py FROM cand JOIN {r}_v v ON v.oid = rid AND i = 0), {_inside('pr', s, 'rid', 'sid', 'in_s')}"
    return f"""WITH {duckdb_layer(r)}, {duckdb_layer(s)}, {edges(r)}, {edges(s, not line)}, {candidates(r, s)},
crossed AS (SELECT DISTINCT rid, sid FROM (SELECT rid, sid, {_sides('a', 'b')} FROM cand JOIN {r}_e a ON a.oid = rid JOIN {s}_e b ON b.oid = sid WHERE {_BOXES}) WHERE d1 <= 0 AND d2 <= 0),
ps AS (SELECT rid, sid, x AS px, y AS py FROM cand JOIN {s}_v v ON v.oid = sid AND i = 0), {_inside('ps', r, 'sid', 'rid', 'in_r')}{more},
result AS (SELECT * FROM crossed UNION SELECT * FROM in_r {'' if line else 'UNION SELECT * FROM in_s'})"""


def exact_within(r: str, s: str) -> str:
    """``WITH`` text up to CTE ``result(rid, sid)``: no proper crossing, and all vertices inside or on the boundary."""
    return f"""WITH {duckdb_layer(r)}, {duckdb_layer(s)}, {edges(r)}, {edges(s)}, {candidates(r, s, True)},
crossed AS (SELECT DISTINCT rid, sid FROM (SELECT rid, sid, {_sides('a', 'b')} FROM cand JOIN {r}_e a ON a.oid = rid JOIN {s}_e b ON b.oid = sid WHERE {_BOXES}) WHERE d1 < 0 AND d2 < 0),
pv AS (SELECT rid, sid, v.i, x AS px, y AS py FROM cand JOIN {r}_v v ON v.oid = rid),
odd AS (SELECT rid, sid, i, count(*) FILTER (WHERE (y0 > py) <> (y1 > py) AND ((x1 - x0) * (py - y0) - (px - x0) * (y1 - y0) > 0) = (y1 > y0)) % 2 = 1 OR bool_or((x1 - x0) * (py - y0) = (y1 - y0) * (px - x0) AND px BETWEEN least(x0, x1) AND greatest(x0, x1) AND py BETWEEN least(y0, y1) AND greatest(y0, y1)) AS ok FROM pv JOIN {s}_e e ON e.oid = sid GROUP BY rid, sid, i),
result AS (SELECT rid, sid FROM odd GROUP BY ALL HAVING bool_and(ok) EXCEPT SELECT * FROM crossed)"""


# ---- lists, sizes and tests of the constructions ----


def run_lists(name: str, order: int) -> str:
    """CTE ``{name}_runs(oid, list, st, en)`` after ``cells``."""
    return f"""{name}_ids AS ({duckdb_ids(f"(SELECT oid, 'cover' AS list, cx, cy FROM {name}_cells UNION ALL SELECT oid, 'core', cx, cy FROM {name}_core)", 'oid, list', order)}),
{name}_m AS (SELECT oid, list, h, h - row_number() OVER (PARTITION BY oid, list ORDER BY h) AS g FROM {name}_ids),
{name}_runs AS MATERIALIZED (SELECT oid, list, min(h) AS st, max(h) + 1 AS en FROM {name}_m GROUP BY oid, list, g)"""


_VBYTE = "1 + (gap >= 128)::INT + (gap >= 16384)::INT + (gap >= 2097152)::INT + (gap >= 268435456)::INT"


def list_bytes(name: str) -> str:
    """CTE ``{name}_bytes(oid, list, ends, bytes, code)`` after ``run_lists``: list ends, compressed bytes, bytes of the codes."""
    return f"""{name}_ends AS (SELECT oid, list, en - st AS size, st, en, coalesce(lag(en) OVER (PARTITION BY oid, list ORDER BY st), 0) AS before FROM {name}_runs),
{name}_gaps AS (SELECT oid, list, (3 * size + 7) // 8 AS code, unnest([st - before, en - st]) AS gap, unnest([1, 0]) AS head FROM {name}_ends),
{name}_bytes AS MATERIALIZED (SELECT oid, list, count(*) AS ends, CAST(sum({_VBYTE}) AS BIGINT) AS bytes, CAST(sum(head * code) AS BIGINT) AS code FROM {name}_gaps GROUP BY oid, list)"""


def space(name: str, order: int, max_cells: int = 750) -> str:
    """One SELECT of (layer, kind, bytes) for a layer's representations."""
    total = lambda kind, size, source: f"SELECT '{name}' AS layer, '{kind}' AS kind, CAST(coalesce(sum({size}), 0) AS BIGINT) AS bytes FROM {source}"
    lists = f"WITH {duckdb_layer(name)}, {cells(name, order)}, {gap_lists(name, order)}, {list_bytes(name)}"
    raster = f"WITH {duckdb_layer(name)}, {cells(name, None, max_cells=max_cells)}, sizes AS (SELECT oid, count(*) AS n FROM {name}_cells GROUP BY oid)"
    hull = f"WITH {duckdb_layer(name)}, {hulls(name)}, sizes AS (SELECT oid, count(*) AS h FROM {name}_hull GROUP BY oid)"
    return " UNION ALL ".join(
        f"SELECT * FROM ({x})"
        for x in (
            f"WITH {duckdb_layer(name)} {total('geometry', '16 * n', name)} UNION ALL {total('box', '36', name)}",
            f"{lists} {total('dual', '4 * ends', f'{name}_bytes')} UNION ALL {total('dual_compressed', 'bytes', f'{name}_bytes')} UNION ALL " + total("coded", "4 * ends + code", f"{name}_bytes WHERE list = 'cover'"),
            f"{raster} {total('local_raster', '16 + (n + 3) // 4', 'sizes')}",
            f"{hull} {total('corner_hull', '16 * (least(h, 5) + h)', 'sizes')}",
        )
    )


def ratios(space_sql: str) -> str:
    """How many times smaller dual lists are than coded ones, in basis points: least, most and mean over layers."""
    return f"""WITH sizes AS MATERIALIZED ({space_sql}) SELECT kind, min(bp) AS least, max(bp) AS most, CAST(sum(bp) // count(*) AS BIGINT) AS mean FROM (
SELECT b.kind, a.bytes * 10000 // b.bytes AS bp FROM sizes a JOIN sizes b ON a.layer = b.layer AND a.kind = 'coded' AND b.kind IN ('dual', 'dual_compressed')) GROUP BY kind"""


def gaps(name: str, order: int) -> str:
    """CTE ``{name}_gap(oid, st, cx, cy, root)`` after ``cells``: the first cell of each gap, and whether no earlier neighbour labels it."""
    near = "(VALUES (1, 0), (-1, 0), (0, 1), (0, -1)) n(sx, sy)"
    top = (1 << order) - 1
    return f"""{name}_q1 AS ({duckdb_ids(f'{name}_edge', 'oid', order)}),
{name}_q2 AS (SELECT oid, h, cx, cy, lead(h) OVER (PARTITION BY oid ORDER BY h) AS nxt FROM {name}_q1),
{name}_q3 AS (SELECT oid, h, nxt, cx + sx AS cx, cy + sy AS cy FROM {name}_q2, {near} WHERE nxt > h + 1 AND cx + sx BETWEEN 0 AND {top} AND cy + sy BETWEEN 0 AND {top}),
{name}_q4 AS (SELECT oid, h AS st, nxt AS en, cx, cy FROM ({duckdb_ids(f'(SELECT oid, h AS before, nxt, cx, cy FROM {name}_q3)', 'oid, before, nxt', order)}) WHERE h = before + 1),
{name}_q5 AS (SELECT oid, st, cx AS gx, cy AS gy, cx + sx AS cx, cy + sy AS cy FROM {name}_q4, {near} WHERE cx + sx BETWEEN 0 AND {top} AND cy + sy BETWEEN 0 AND {top}),
{name}_q6 AS ({duckdb_ids(f'{name}_q5', 'oid, st, gx, gy', order)}),
{name}_led AS (SELECT DISTINCT oid, st FROM {name}_q6 q WHERE h < st AND NOT EXISTS (SELECT 1 FROM {name}_edge e WHERE e.oid = q.oid AND e.cx = q.cx AND e.cy = q.cy)),
{name}_gap AS MATERIALIZED (SELECT g.oid, g.st, g.en, cx, cy, l.st IS NULL AS root FROM {name}_q4 g LEFT JOIN {name}_led l ON l.oid = g.oid AND l.st = g.st)"""


def gap_lists(name: str, order: int) -> str:
    """CTE ``{name}_runs(oid, list, st, en)`` after ``cells``, without naming interior cells: a gap is tested by its first cell.

    Where the queries of the constructions compare cell by cell, this serves large objects at fine orders.
    """
    return f"""{gaps(name, order)},
{name}_in AS MATERIALIZED (SELECT g.oid, g.st, g.en FROM {name}_gap g JOIN {name}_x e ON e.oid = g.oid AND e.cy = g.cy
  WHERE ((x1 - x0) * ((2 * g.cy + 1) * s - 2 * y0) - ((2 * g.cx + 1) * s - 2 * x0) * (y1 - y0) > 0) = (y1 > y0) GROUP BY g.oid, g.st, g.en HAVING count(*) % 2 = 1),
{name}_seg AS (SELECT oid, h AS st, h + 1 AS en FROM {name}_q1 UNION ALL SELECT oid, st, en FROM {name}_in),
{name}_isl AS (SELECT *, CASE WHEN st = lag(en) OVER (PARTITION BY oid ORDER BY st) THEN 0 ELSE 1 END AS fresh FROM {name}_seg),
{name}_num AS (SELECT *, sum(fresh) OVER (PARTITION BY oid ORDER BY st ROWS UNBOUNDED PRECEDING) AS g FROM {name}_isl),
{name}_runs AS MATERIALIZED (SELECT oid, 'cover' AS list, min(st) AS st, max(en) AS en FROM {name}_num GROUP BY oid, g UNION ALL SELECT oid, 'core', st, en FROM {name}_in)"""


def regions(name: str) -> str:
    """CTE ``{name}_regions(n)`` after ``cells``: connected areas of the box without edge cells (``WITH RECURSIVE``).

    Unlabelled stretches of a row are linked to overlapping ones of the row above; a region is
    what its first stretch reaches.
    """
    return f"""{name}_free AS (SELECT oid, cx, cy, cx - row_number() OVER (PARTITION BY oid, cy ORDER BY cx) AS g FROM ({name}_w2 ANTI JOIN {name}_edge USING (oid, cx, cy))),
{name}_span AS MATERIALIZED (SELECT oid, cy, min(cx) AS a, max(cx) AS b, row_number() OVER (PARTITION BY oid ORDER BY cy, min(cx)) AS i FROM {name}_free GROUP BY oid, cy, g),
{name}_up AS (SELECT x.oid, x.i, y.i AS j FROM {name}_span x JOIN {name}_span y ON x.oid = y.oid AND y.cy = x.cy + 1 AND x.a <= y.b AND y.a <= x.b),
{name}_next AS MATERIALIZED (SELECT oid, i, j FROM {name}_up UNION ALL SELECT oid, j, i FROM {name}_up),
{name}_reach AS (SELECT oid, i AS root, i FROM {name}_span UNION SELECT r.oid, r.root, n.j FROM {name}_reach r JOIN {name}_next n ON n.oid = r.oid AND n.i = r.i WHERE n.j > r.root),
{name}_regions AS (SELECT count(*) AS n FROM {name}_span s WHERE NOT EXISTS (SELECT 1 FROM {name}_reach r WHERE r.oid = s.oid AND r.i = s.i AND r.root < s.i))"""


# ---- space partitions ----


def tiled(names: tuple[str, ...], p: int, order: int, only: int | None = None) -> str:
    """CTEs of layers ``t_{name}`` whose objects are the replicas of p x p tiles, each on its tile's own grid."""
    reach = lambda a: f"unnest(range({a}min * {p} // {DOMAIN}, {a}max * {p} // {DOMAIN} + 1))"
    out = [duckdb_layer(n, only) for n in names]
    for n in names:
        out.append(f"{n}_r1 AS (SELECT *, {reach('x')} AS tx FROM {n}), {n}_r2 AS (SELECT *, {reach('y')} AS ty FROM {n}_r1), {n}_rep AS (SELECT *, tx * {p} + ty AS tile FROM {n}_r2)")
    every = " UNION ALL ".join(f"SELECT tile, xmin, ymin, xmax, ymax FROM {n}_rep" for n in names)
    out.append(f"""tile_ext AS (SELECT tile, min(xmin) AS bx, min(ymin) AS by_, greatest(max(xmax) - min(xmin), max(ymax) - min(ymin)) AS ext FROM ({every}) GROUP BY tile),
tile_box AS (SELECT tile, s, bx - s AS gx, by_ - s AS gy FROM (SELECT *, (ext + {(1 << order) - 2}) // {(1 << order) - 2} AS s FROM tile_ext))""")
    for n in names:
        key = f"tile * {10**10} + oid"
        out.append(f"""t_{n} AS (SELECT {key} AS oid, oid AS o, tile, xmin AS x_, ymin AS y_, xmin - gx AS xmin, ymin - gy AS ymin, xmax - gx AS xmax, ymax - gy AS ymax FROM {n}_rep JOIN tile_box USING (tile)),
t_{n}_v AS (SELECT {key} AS oid, i, x - gx AS x, y - gy AS y FROM {n}_rep JOIN tile_box USING (tile) JOIN {n}_v USING (oid)),
t_{n}_s AS (SELECT {key} AS oid, s::BIGINT AS s, 0 AS k FROM {n}_rep JOIN tile_box USING (tile))""")
    return "WITH RECURSIVE " + ", ".join(out)


def tiled_verdicts(r: str, s: str, p: int, order: int, only: int | None = None) -> str:
    """The dual filter within tiles; the tile of the common box's lower corner owns a pair."""
    a, b = f"t_{r}", f"t_{s}"
    own = f"greatest(r.x_, s.x_) * {p} // {DOMAIN} * {p} + greatest(r.y_, s.y_) * {p} // {DOMAIN} = r.tile"
    boxes = "r.xmin <= s.xmax AND s.xmin <= r.xmax AND r.ymin <= s.ymax AND s.ymin <= r.ymax"
    text = ", ".join(cells(x, None, sides="") for x in (a, b))
    return f"""{tiled((r, s), p, order, only)}, {text}, cand AS (SELECT r.oid AS rid, s.oid AS sid FROM {a} r JOIN {b} s ON r.tile = s.tile AND {boxes} WHERE {own}), {shared(a, b)},
verdicts AS (SELECT rid, sid, {VERDICT} AS verdict, {merges('CC,CK,KC')} AS merges FROM cand LEFT JOIN met USING (rid, sid))"""


def tiled_bytes(name: str, p: int, order: int) -> str:
    """One SELECT of the bytes of all lists of a partitioned layer."""
    x = f"t_{name}"
    text = cells(x, None, sides="")
    return f"SELECT '{name}' AS layer, {p} AS tiles, * FROM ({tiled((name,), p, order)}, {text}, {gap_lists(x, order)} SELECT CAST(8 * count(*) AS BIGINT) AS bytes FROM {x}_runs)"
