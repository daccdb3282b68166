"""Hilbert curve ids of grid cells, top-down: a cell's id at a lower order is a prefix of its id at a higher one.

A walk from the highest bit keeps two flags, ``f`` (both axes mirrored) and
``w`` (axes swapped); mirroring both axes commutes with swapping them, so the
flags carry the whole orientation.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


#: Levels that one table look-up takes.
_STEP = 6


def _walk(bits, f, w, levels: int, forward: bool):
    """``levels`` levels from the flags on, bit by bit: (ids or cells, flags).  ``bits``: (cx, cy) or (id,)."""
    out = [np.zeros_like(bits[0]) for _ in range(1 if forward else 2)]
    for i in range(levels - 1, -1, -1):
        if forward:
            bx, by = (bits[0] >> i) & 1, (bits[1] >> i) & 1
            swap = w * (bx ^ by)
            rx, ry = bx ^ swap ^ f, by ^ swap ^ f
            out[0] = (out[0] << 2) | ((3 * rx) ^ ry)
        else:
            q = (bits[0] >> (2 * i)) & 3
            rx = q >> 1
            ry = (q ^ rx) & 1
            a, b = rx ^ f, ry ^ f
            swap = w * (a ^ b)
            out = [(out[0] << 1) | (a ^ swap), (out[1] << 1) | (b ^ swap)]
        still = 1 - ry
        f, w = f ^ (still & rx), w ^ still
    return out, f, w


def _tables(step: int) -> tuple[np.ndarray, np.ndarray]:
    """For each orientation and ``step`` levels of input: output bits with the next orientation in the two low bits."""
    n, low = 1 << (2 * step), (1 << step) - 1
    state, x = np.divmod(np.arange(4 * n), n)
    (d,), f, w = _walk((x >> step, x & low), state >> 1, state & 1, step, True)
    (cx, cy), g, v = _walk((x,), state >> 1, state & 1, step, False)
    return (d << 2 | f << 1 | w).astype(np.int32), ((cx << step | cy) << 2 | g << 1 | v).astype(np.int32)


_TABLES = {k: _tables(k) for k in range(1, _STEP + 1)}


def _strides(order: int) -> list[tuple[int, int]]:
    """(levels, lowest level) of the look-ups from the top."""
    steps = [order % _STEP] * (order % _STEP > 0) + [_STEP] * (order // _STEP)
    return [(k, order - sum(steps[: i + 1])) for i, k in enumerate(steps)]


def encode(cx: np.ndarray, cy: np.ndarray, order: int) -> np.ndarray:
    """Ids of cells at an order."""
    cx, cy = np.asarray(cx, np.int64), np.asarray(cy, np.int64)
    d, state = np.zeros_like(cx), 0
    for k, i in _strides(order):
        low = (1 << k) - 1
        got = _TABLES[k][0][state << (2 * k) | ((cx >> i) & low) << k | (cy >> i) & low]
        d <<= 2 * k
        d |= got >> 2
        state = got & 3
    return d


def decode(hid: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Cells of ids at an order."""
    hid = np.asarray(hid, np.int64)
    cx, cy, state = np.zeros_like(hid), np.zeros_like(hid), 0
    for k, i in _strides(order):
        got = _TABLES[k][1][state << (2 * k) | (hid >> (2 * i)) & ((1 << 2 * k) - 1)]
        cx <<= k
        cx |= got >> (2 + k)
        cy <<= k
        cy |= (got >> 2) & ((1 << k) - 1)
        state = got & 3
    return cx, cy


def _levels(order: int) -> Column:
    return F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1))


def hilbert_id(cx: Column, cy: Column, order: int) -> Column:
    """``encode`` as a Catalyst expression: one fold over the levels, no Python."""
    x, y = cx.cast("long"), cy.cast("long")

    def step(s: Column, i: Column) -> Column:
        bx, by = F.getbit(s["x"], i).cast("int"), F.getbit(s["y"], i).cast("int")
        swap = s["w"] * bx.bitwiseXOR(by)
        rx, ry = bx.bitwiseXOR(swap).bitwiseXOR(s["f"]), by.bitwiseXOR(swap).bitwiseXOR(s["f"])
        d = s["d"] * 4 + (rx * 3).bitwiseXOR(ry)
        still = F.lit(1) - ry
        return F.struct(d.alias("d"), s["f"].bitwiseXOR(still * rx).alias("f"), s["w"].bitwiseXOR(still).alias("w"), s["x"].alias("x"), s["y"].alias("y"))

    # the operands travel in the state, so that nested expressions are evaluated once
    return F.aggregate(_levels(order), F.struct(F.lit(0).cast("long").alias("d"), F.lit(0).alias("f"), F.lit(0).alias("w"), x.alias("x"), y.alias("y")), step, lambda s: s["d"])


def hilbert_cell(hid: Column, order: int) -> Column:
    """``decode`` as a Catalyst expression: struct(cx, cy)."""
    h = hid.cast("long")

    def step(s: Column, i: Column) -> Column:
        rx = F.getbit(s["h"], i * 2 + 1).cast("int")
        ry = F.getbit(s["h"], i * 2).cast("int").bitwiseXOR(rx)
        a, b = rx.bitwiseXOR(s["f"]), ry.bitwiseXOR(s["f"])
        swap = s["w"] * a.bitwiseXOR(b)
        still = F.lit(1) - ry
        return F.struct((s["cx"] * 2 + a.bitwiseXOR(swap)).alias("cx"), (s["cy"] * 2 + b.bitwiseXOR(swap)).alias("cy"), s["f"].bitwiseXOR(still * rx).alias("f"), s["w"].bitwiseXOR(still).alias("w"), s["h"].alias("h"))

    zero = F.lit(0).cast("long")
    return F.aggregate(_levels(order), F.struct(zero.alias("cx"), zero.alias("cy"), F.lit(0).alias("f"), F.lit(0).alias("w"), h.alias("h")), step, lambda s: F.struct(s["cx"].alias("cx"), s["cy"].alias("cy")))


def coarsen_id(hid: Column, order: int, to: int) -> Column:
    """The id of the cell that holds a cell at a lower order."""
    return F.shiftright(hid, 2 * (order - to))


def duckdb_hilbert(x: str, y: str, order: int) -> str:
    """The same fold in DuckDB SQL, for oracles."""
    bx, by = f"(({x} >> i) & 1)", f"(({y} >> i) & 1)"
    swap = f"(s.w * xor({bx}, {by}))"
    rx, ry = f"xor(xor({bx}, {swap}), s.f)", f"xor(xor({by}, {swap}), s.f)"
    body = f"{{'d': s.d * 4 + xor(3 * {rx}, {ry}), 'f': xor(s.f, (1 - {ry}) * {rx}), 'w': xor(s.w, 1 - {ry}), 'i': 0::BIGINT}}"
    # the accumulator and the elements share a type, so levels travel in its last field
    body = body.replace("i)", "e.i)")
    levels = "[" + ", ".join(f"{{'d': 0::BIGINT, 'f': 0::BIGINT, 'w': 0::BIGINT, 'i': {i}::BIGINT}}" for i in range(order - 1, -1, -1)) + "]"
    return f"list_reduce({levels}, lambda s, e: {body}, {{'d': 0::BIGINT, 'f': 0::BIGINT, 'w': 0::BIGINT, 'i': 0::BIGINT}}).d"


def duckdb_ids(source: str, keys: str, order: int) -> str:
    """``SELECT keys, h`` of a relation with cells (cx, cy): a level of the curve is a subquery, which suits many cells."""
    q = f"SELECT {keys}, cx, cy, 0::BIGINT AS d, 0::BIGINT AS f, 0::BIGINT AS w FROM {source}"
    for i in range(order - 1, -1, -1):
        q = f"SELECT *, w * xor((cx >> {i}) & 1, (cy >> {i}) & 1) AS sw FROM ({q})"
        q = f"SELECT * EXCLUDE (sw), xor(xor((cx >> {i}) & 1, sw), f) AS rx, xor(xor((cy >> {i}) & 1, sw), f) AS ry FROM ({q})"
        q = f"SELECT {keys}, cx, cy, d * 4 + xor(3 * rx, ry) AS d, xor(f, (1 - ry) * rx) AS f, xor(w, 1 - ry) AS w FROM ({q})"
    return f"SELECT {keys}, cx, cy, d AS h FROM ({q})"
