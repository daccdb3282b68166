"""Gap and variable-byte coding of sorted lists: the first value, then differences, 7 bits a byte.

A byte below 128 ends a value.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def gaps(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    out = np.diff(values, prepend=0)
    first = offsets[:-1][offsets[:-1] < offsets[1:]]
    out[first] = values[first]
    return out


def sizes(g: np.ndarray) -> np.ndarray:
    """Bytes of each value."""
    return 1 + sum((g >= 1 << (7 * k)).astype(np.int64) for k in range(1, 9))


def encode(values: np.ndarray, offsets: np.ndarray) -> pa.Array:
    """A list column's values as one binary a row."""
    g = gaps(values, offsets)
    n = sizes(g)
    ends = np.cumsum(n)
    owner = np.repeat(np.arange(len(g)), n)
    place = np.arange(ends[-1] if len(ends) else 0) - (ends - n)[owner]
    out = ((g[owner] >> (7 * place)) & 127).astype(np.uint8)
    out[place < n[owner] - 1] |= 128
    cut = np.concatenate([[0], ends])[offsets].astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(cut.tobytes()), pa.py_buffer(out.tobytes())])


def _values(data: np.ndarray) -> np.ndarray:
    """Differences in a byte string that ends with a whole value."""
    if not len(data):
        return np.zeros(0, np.int64)
    last = np.flatnonzero(data < 128)
    first = np.concatenate([[0], last[:-1] + 1])
    place = np.arange(len(data)) - np.repeat(first, last - first + 1)
    return np.add.reduceat((data & 127).astype(np.int64) << (7 * place), first)


def decode(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The inverse of ``encode`` for a batch (nulls as empty lists)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    rows = [x or b"" for x in column.to_pylist()]
    data = np.frombuffer(b"".join(rows), np.uint8)
    g = _values(data)
    ends = np.concatenate([[0], np.cumsum(data < 128)])
    offsets = ends[np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)]
    total = np.cumsum(g)
    base = np.concatenate([[0], total])[offsets[:-1]]
    return total - np.repeat(base, np.diff(offsets)), offsets


def deflate(column: pa.Array) -> pa.Array:
    """Each binary after a byte that says how it is kept: 1 deflated, 0 as it is, where deflating doesn't shorten it."""
    small = ((x, zlib.compress(x, 6)) for x in column.to_pylist())
    return pa.array([b"\x01" + z if len(z) < len(x) else b"\x00" + x for x, z in small], pa.binary())


def inflate(column: pa.Array) -> pa.Array:
    """The inverse of ``deflate`` (nulls as empty binaries)."""
    return pa.array([(zlib.decompress(x[1:]) if x[0] else x[1:]) if x else b"" for x in column.to_pylist()], pa.binary())


class Cursor:
    """Decodes a coded list block by block, so that a merge can stop before the end."""

    def __init__(self, data: bytes, block: int = 256):
        self.data, self.block, self.at, self.last, self.read = np.frombuffer(data, np.uint8), block, 0, 0, 0

    def next(self) -> np.ndarray | None:
        """The next values (whole runs), or None at the end."""
        if self.at >= len(self.data):
            return None
        end = min(len(self.data), self.at + self.block)
        stop = np.flatnonzero(self.data[self.at : end] < 128)
        while len(stop) < 2:
            end = min(len(self.data), end + self.block)
            stop = np.flatnonzero(self.data[self.at : end] < 128)
        stop = stop[: len(stop) // 2 * 2]
        part = self.data[self.at : self.at + stop[-1] + 1]
        self.at += len(part)
        self.read += len(part)
        out = np.cumsum(_values(part)) + self.last
        self.last = int(out[-1])
        return out


def cursors_overlap(a: Cursor, b: Cursor) -> bool:
    """Merge two coded run lists while decoding; stops at the first shared id."""
    x, y = a.next(), b.next()
    while x is not None and y is not None:
        at = np.searchsorted(y[1::2], x[0::2], "right")
        ok = at < len(y) // 2
        if (y[0::2][at[ok]] < x[1::2][ok]).any():
            return True
        if x[-1] <= y[-1]:
            x = a.next()
        else:
            y = b.next()
    return False


class Cursors:
    """Decodes the coded lists of many rows block by block; row i reads list ``at[i]`` of the column."""

    def __init__(self, column: pa.Array, at: np.ndarray, block: int = 256):
        if block < 20:
            raise ValueError("a block must hold a whole run of two values")
        parts = [x or b"" for x in column.to_pylist()]
        off = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int64)
        self.data, self.block = np.frombuffer(b"".join(parts), np.uint8), block
        self.at, self.end = off[:-1][at], off[1:][at]
        self.last, self.read = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)

    def next(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The next values (whole runs) of distinct rows, as values and offsets; none at a list's end."""
        size = np.minimum(self.end[rows] - self.at[rows], self.block)
        row = np.repeat(np.arange(len(rows)), size)
        place = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
        stop = np.flatnonzero(self.data[self.at[rows][row] + place] < 128)
        n = np.bincount(row[stop], minlength=len(rows)) // 2 * 2
        nth = np.arange(len(stop)) - np.repeat(np.cumsum(np.bincount(row[stop], minlength=len(rows))) - np.bincount(row[stop], minlength=len(rows)), np.bincount(row[stop], minlength=len(rows)))
        used = np.zeros(len(rows), np.int64)
        final = stop[nth == n[row[stop]] - 1]
        used[row[final]] = place[final] + 1
        part = self.data[self.at[rows][row] + place][place < used[row]]
        offsets = np.concatenate([[0], np.cumsum(n)])
        total = np.cumsum(_values(part))
        base = np.concatenate([[0], total])[offsets[:-1]] - self.last[rows]
        values = total - np.repeat(base, n)
        some = n > 0
        self.last[rows[some]] = values[offsets[1:][some] - 1]
        self.at[rows] += used
        self.read[rows] += used
        return values, offsets


def gap_column(values: Column) -> Column:
    """Differences of an array column as a Catalyst expression, the first value kept."""
    return F.transform(values, lambda v, i: F.when(i == 0, v).otherwise(v - F.get(values, i - 1)))


def vbyte_size(gap: Column) -> Column:
    """Bytes of a difference, as a Catalyst expression."""
    return sum((F.when(gap >= (1 << (7 * k)), 1).otherwise(0) for k in range(1, 9)), F.lit(1))
