"""Approximations of layers: dual runs, coded runs, local rasters, corners with hull, line cells.

All are narrow Arrow stages over the layer's own partitions: no shuffle, and
memory bounded by a chunk of boundary cells.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.functions import codec, geometry, lists
from rasterruns.functions.pairtests import pieces
from rasterruns.grid import DOMAIN, GridSpec
from rasterruns.operators import rasterize

#: Codes of weak, strong and full cells for a left-hand (R) and a right-hand (S) list.
CODES = {"R": {1: 0b100, 2: 0b101, 3: 0b011}, "S": {1: 0b010, 2: 0b011, 3: 0b101}}
SWAP = 0b110
#: Cells of local rasters built at once: few enough for a core's cache.
_WINDOWS = 65_536


def points(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Points and offsets of a column of rings, as structs or as flat coordinates."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    f = column.flatten()
    if pa.types.is_integer(f.type):
        return f.to_numpy().astype(np.int64).reshape(-1, 2), np.concatenate([[0], np.cumsum(sizes // 2)]).astype(np.int64)
    return np.stack([f.field("x").to_numpy(), f.field("y").to_numpy()], axis=1).astype(np.int64), np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)


def _batches(batch: pa.RecordBatch, column: str, grid: GridSpec, closed: bool = True):
    pts, off = points(batch.column(column))
    whole = rasterize.Batch(pts, off, grid, closed)
    for a, b in whole.chunks():
        yield a, b, whole.part(a, b)


def _grids(batch: pa.RecordBatch, grid: GridSpec | None):
    """The batch itself with one grid, or its rows by the grid of their tile."""
    if grid is not None:
        yield batch, grid
        return
    keys = list(zip(*(batch.column(c).to_pylist() for c in ("g_order", "g_x0", "g_y0", "g_cell")), strict=True))
    for key in sorted(set(keys)):
        rows = pa.array([i for i, k in enumerate(keys) if k == key])
        yield pa.RecordBatch.from_arrays([c.take(rows) for c in batch.columns], names=batch.schema.names), GridSpec(*key)


def build_dual(layer: DataFrame, grid: GridSpec | None = None, method: str = "onestep_neighbours", compressed: bool = False) -> DataFrame:
    """``(tile_id, oid, ord, cover, core, n_edge, n_gaps, n_pip)``; lists as binaries if compressed.

    Without ``grid`` the layer brings each row's grid (g_order, g_x0, g_y0,
    g_cell) and tile_id, as tiles.assign leaves it.
    """
    kind = "binary" if compressed else "array<bigint>"
    extra = ", n_cover int, n_core int" if compressed else ""
    schema = f"tile_id int, oid long, ord int, cover {kind}, core {kind}, n_edge int, n_gaps int, n_pip int{extra}"
    columns = ["oid", "ring"] if grid is not None else ["oid", "ring", "tile_id", "g_order", "g_x0", "g_y0", "g_cell"]
    return layer.select(*columns).mapInArrow(dual_rows(grid, method, compressed), schema)


def dual_rows(grid: GridSpec | None = None, method: str = "onestep_neighbours", compressed: bool = False):
    """The function from batches (oid, ring) to batches of dual runs."""
    if method not in rasterize.METHODS:
        raise ValueError(f"unknown construction {method}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = rasterize.METHODS[method]
        for batch in batches:
            for rows, g in _grids(batch, grid):
                for a, b, part in _batches(rows, "ring", g):
                    got = make(part)
                    n = b - a
                    if compressed:
                        both = [codec.encode(*got[c]) for c in ("cover", "core")]
                        tail = [pa.array((np.diff(got[c][1]) // 2).astype(np.int32)) for c in ("cover", "core")]
                    else:
                        both, tail = [lists.to_column(*got[c]) for c in ("cover", "core")], []
                    tile = rows.column("tile_id").slice(a, n).cast(pa.int32()) if grid is None else pa.array(np.zeros(n, np.int32))
                    counts = [pa.array(got[c].astype(np.int32)) for c in ("n_edge", "n_gaps", "n_pip")]
                    names = ["tile_id", "oid", "ord", "cover", "core", "n_edge", "n_gaps", "n_pip", "n_cover", "n_core"]
                    out = [tile, rows.column("oid").slice(a, n), pa.array(np.full(n, g.order, np.int32)), *both, *counts, *tail]
                    yield pa.RecordBatch.from_arrays(out, names=names[: len(out)])

    return run


def compress(dual: DataFrame) -> DataFrame:
    """Dual runs with gap and variable-byte coded lists."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            both = [lists.flat(batch.column(c)) for c in ("cover", "core")]
            keep = [batch.column(c) for c in ("tile_id", "oid", "ord")]
            yield pa.RecordBatch.from_arrays([*keep, *(codec.encode(*x) for x in both), *(pa.array((np.diff(x[1]) // 2).astype(np.int32)) for x in both)], names=["tile_id", "oid", "ord", "cover", "core", "n_cover", "n_core"])

    return dual.select("tile_id", "oid", "ord", "cover", "core").mapInArrow(run, "tile_id int, oid long, ord int, cover binary, core binary, n_cover int, n_core int")


def decompress(coded: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [batch.column(c) for c in ("tile_id", "oid", "ord")]
            yield pa.RecordBatch.from_arrays([*keep, *(lists.to_column(*codec.decode(batch.column(c))) for c in ("cover", "core"))], names=["tile_id", "oid", "ord", "cover", "core"])

    return coded.select("tile_id", "oid", "ord", "cover", "core").mapInArrow(run, "tile_id int, oid long, ord int, cover array<bigint>, core array<bigint>")


def edge_cells(layer: DataFrame, grid: GridSpec, column: str = "ring") -> DataFrame:
    """``(oid, cx, cy, hid)`` of the cells that boundaries (or paths) enter."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for a, _, part in _batches(batch, column, grid, column == "ring"):
                o, h = rasterize.edge_ids(part)
                x, y = rasterize.hilbert.decode(h, grid.order)
                yield pa.RecordBatch.from_arrays([pa.array(ids[a + o]), pa.array(x), pa.array(y), pa.array(h)], names=["oid", "cx", "cy", "hid"])

    return layer.select("oid", column).mapInArrow(run, "oid long, cx long, cy long, hid long")


def coverage_cells(layer: DataFrame, grid: GridSpec, clip_all: bool = False) -> DataFrame:
    """``(oid, hid, coverage, type)`` of all cells that are not empty (1 weak, 2 strong, 3 full)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for a, _, part in _batches(batch, "ring", grid):
                o, h, share, kind = rasterize.coverage(part, clip_all)
                yield pa.RecordBatch.from_arrays([pa.array(ids[a + o]), pa.array(h), pa.array(share), pa.array(kind.astype(np.int32))], names=["oid", "hid", "coverage", "type"])

    return layer.select("oid", "ring").mapInArrow(run, "oid long, hid long, coverage double, type int")


def pack_codes(kind: np.ndarray, run_of: np.ndarray, size: np.ndarray, side: str) -> tuple[np.ndarray, np.ndarray]:
    """3-bit codes of cells, a run's codes joined and padded to bytes: (bytes, byte offset of each run)."""
    table = np.zeros(4, np.uint8)
    for t, c in CODES[side].items():
        table[t] = c
    start = np.concatenate([[0], np.cumsum((3 * size + 7) // 8)])
    bits = np.zeros(8 * start[-1], np.uint8)
    inside = np.arange(len(kind)) - np.repeat(np.cumsum(size) - size, size)
    at = 8 * start[:-1][run_of] + 3 * inside
    code = table[kind]
    for j in range(3):
        bits[at + j] = (code >> (2 - j)) & 1
    return np.packbits(bits), start


def build_coded(layer: DataFrame, grid: GridSpec, side: str = "R", clip_all: bool = False, compressed: bool = False) -> DataFrame:
    """``(oid, runs, code, side)``: flat run bounds, and the runs' codes one after the other.

    ``compressed``: bounds as a binary of gaps, codes deflated where that shortens them.
    """
    return layer.select("oid", "ring").mapInArrow(coded_rows(grid, side, clip_all, compressed), f"oid long, runs {'binary' if compressed else 'array<bigint>'}, code binary, side string")


def coded_rows(grid: GridSpec, side: str = "R", clip_all: bool = False, compressed: bool = False):
    """The function from batches (oid, ring) to batches of coded runs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, part in _batches(batch, "ring", grid):
                o, h, _, kind = rasterize.coverage(part, clip_all)
                values, off = rasterize.runs(o, h, part.n)
                size = values[1::2] - values[0::2]
                data, start = pack_codes(kind, np.repeat(np.arange(len(size)), size), size, side)
                cut = start[off // 2].astype(np.int32)
                code = pa.Array.from_buffers(pa.binary(), part.n, [None, pa.py_buffer(cut.tobytes()), pa.py_buffer(data.tobytes())])
                both = (codec.encode(values, off), codec.deflate(code)) if compressed else (lists.to_column(values, off), code)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), *both, pa.array([side] * part.n)], names=["oid", "runs", "code", "side"])

    return run


def cell_codes(coded: DataFrame) -> DataFrame:
    """``(oid, hid, code)`` of every cell of coded runs (compressed or not), read back from the packed bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = pa.types.is_binary(batch.column("runs").type)
            values, off = codec.decode(batch.column("runs")) if packed else lists.flat(batch.column("runs"))
            codes = codec.inflate(batch.column("code")) if packed else batch.column("code")
            size = values[1::2] - values[0::2]
            first = np.concatenate([[0], np.cumsum((3 * size + 7) // 8)])[:-1]
            bits = np.unpackbits(np.frombuffer(b"".join(codes.to_pylist()), np.uint8))
            run_of = np.repeat(np.arange(len(size)), size)
            k = np.arange(len(run_of)) - np.repeat(np.cumsum(size) - size, size)
            at = 8 * first[run_of] + 3 * k
            row = np.repeat(np.arange(batch.num_rows), np.diff(off) // 2)[run_of]
            code = bits[at] << 2 | bits[at + 1] << 1 | bits[at + 2]
            yield pa.RecordBatch.from_arrays([batch.column("oid").take(pa.array(row)), pa.array(values[0::2][run_of] + k), pa.array(code.astype(np.int32))], names=["oid", "hid", "code"])

    return coded.select("oid", "runs", "code").mapInArrow(run, "oid long, hid long, code int")


def build_line_cells(lines: DataFrame, grid: GridSpec, as_runs: bool = False) -> DataFrame:
    """``(oid, cells)``: sorted ids of the cells a path enters, or the same as runs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, part in _batches(batch, "path", grid, closed=False):
                o, h = rasterize.edge_ids(part)
                cells = rasterize.runs(o, h, part.n) if as_runs else (h, np.searchsorted(o, np.arange(part.n + 1)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), lists.to_column(*cells)], names=["oid", "cells"])

    return lines.select("oid", "path").mapInArrow(run, "oid long, cells array<bigint>")


def raster_level(layer: DataFrame, max_cells: int = 750, unit: int = 1) -> DataFrame:
    """Add ``k``: the least k at which the box takes at most ``max_cells`` cells of side unit * 2^k."""

    def cells(k):
        side = F.call_function("shiftleft", F.lit(unit).cast("long"), k)
        return (F.floor(F.col("xmax") / side) - F.floor(F.col("xmin") / side) + 1) * (F.floor(F.col("ymax") / side) - F.floor(F.col("ymin") / side) + 1)

    return layer.withColumn("k", F.element_at(F.filter(F.sequence(F.lit(0), F.lit(21)), lambda k: cells(k) <= max_cells), 1))


def build_local_raster(layer: DataFrame, max_cells: int = 750, unit: int = 1) -> DataFrame:
    """``(oid, k, cells)``: a private grid of at most ``max_cells`` cells with 4-way types (empty ones left out)."""
    schema = "oid long, k int, cells array<struct<cx:bigint,cy:bigint,type:int>>"
    return raster_level(layer, max_cells, unit).select("oid", "ring", "k").mapInArrow(raster_rows(unit), schema)


def raster_rows(unit: int = 1, windows: bool = False):
    """The function from batches (oid, ring, k) to batches of local rasters, in order of k.

    ``windows``: (oid, k, x0, y0, w, h, types), the types of all cells of the box row by row, instead of a list of cells.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            level = batch.column("k").to_numpy()
            for k in np.unique(level).tolist():
                rows = pa.array(np.flatnonzero(level == k))
                mine = pa.RecordBatch.from_arrays([c.take(rows) for c in batch.columns], names=batch.schema.names)
                side = unit << k
                grid = GridSpec(max(1, (DOMAIN // side).bit_length()), 0, 0, side)
                whole = rasterize.Batch(*points(mine.column("ring")), grid)
                for a, b in pieces(rasterize.window_sizes(whole), _WINDOWS):
                    x0, y0, w, h, off, kind = rasterize.window_types(whole.part(a, b))
                    ids = [mine.column(c).slice(a, b - a) for c in ("oid", "k")]
                    if windows:
                        types = pa.Array.from_buffers(pa.binary(), b - a, [None, pa.py_buffer(off.astype(np.int32).tobytes()), pa.py_buffer(kind.tobytes())])
                        yield pa.RecordBatch.from_arrays([*ids, *(pa.array(v) for v in (x0, y0, w, h)), types], names=["oid", "k", "x0", "y0", "w", "h", "types"])
                        continue
                    at = np.flatnonzero(kind)
                    o = np.searchsorted(off, at, "right") - 1
                    y, x = np.divmod(at - off[o], w[o])
                    x, y = x + x0[o], y + y0[o]
                    order = np.argsort((o << (2 * grid.order)) | rasterize.hilbert.encode(x, y, grid.order))
                    cells = pa.StructArray.from_arrays([pa.array(x[order]), pa.array(y[order]), pa.array(kind[at[order]].astype(np.int32))], names=["cx", "cy", "type"])
                    yield pa.RecordBatch.from_arrays([*ids, pa.ListArray.from_arrays(pa.array(np.searchsorted(at, off).astype(np.int32)), cells)], names=["oid", "k", "cells"])

    return run


def build_corner_hull(layer: DataFrame, column: str = "ring") -> DataFrame:
    """``(oid, corners, hull)``: a convex polygon of at most five corners and the hull, as flat coordinates."""
    return layer.select("oid", column).mapInArrow(hull_rows, "oid long, corners array<double>, hull array<bigint>")


def hull_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From batches (oid, ring) to batches of corners and hulls."""
    for batch in batches:
        hulls = geometry.convex_hulls(*points(batch.column(1)))
        both = [pa.ListArray.from_arrays(pa.array((2 * off).astype(np.int32)), pa.array(pts.ravel())) for pts, off in (geometry.all_five_corners(*hulls), hulls)]
        yield pa.RecordBatch.from_arrays([batch.column(0), *both], names=["oid", "corners", "hull"])


def check_rings(layer: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(good, rejects)``: rejects carry a reason; nothing is dropped silently."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pts, off = points(batch.column(1))
            why = []
            for a, b in zip(off[:-1], off[1:], strict=True):
                ring = pts[a:b]
                why.append("fewer than three points" if len(ring) < 3 else "outside the domain" if ring.min() < 1 or ring.max() >= DOMAIN - 1 else None if geometry.is_simple(ring) else "not simple")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(why, pa.string())], names=["oid", "reason"])

    marks = layer.select("oid", "ring").mapInArrow(run, "oid long, reason string")
    marked = layer.join(marks, "oid")
    return marked.where("reason is null").drop("reason"), marked.where("reason is not null")
