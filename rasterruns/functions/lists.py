"""Kernels over the sorted run lists of a whole batch.

A list column is (values, offsets): flat integers, start at even and end at odd
places, half-open.  The lists of different pairs are kept apart by adding the
pair number times a stride beyond all ids, so one binary search serves a batch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of a list column (nulls as empty lists)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = np.asarray(column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64, copy=False), np.concatenate([[0], np.cumsum(sizes)])


def to_column(values: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values.astype(np.int64)))


def take(lists: tuple[np.ndarray, np.ndarray], rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The lists of some rows."""
    values, offsets = lists
    size = (offsets[1:] - offsets[:-1])[rows]
    out = np.concatenate([[0], np.cumsum(size)])
    at = np.repeat(offsets[:-1][rows] - out[:-1], size) + np.arange(out[-1])
    return values[at], out


def _runs(lists: tuple[np.ndarray, np.ndarray], bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Shifted starts and ends, and the row of each run."""
    values, offsets = lists
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets) // 2)
    shift = row << (bits + 1)
    return values[0::2] + shift, values[1::2] + shift, row


def _bits(*lists: tuple[np.ndarray, np.ndarray]) -> int:
    top = max((int(x[0].max(initial=0)) for x in lists), default=0)
    bits = max(1, top.bit_length())
    if bits + 1 + (len(lists[0][1])).bit_length() > 62:
        raise ValueError("ids too wide for one batch; lower the batch size")
    return bits


def overlap(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Per row: do the two run lists share an id?  O((n + m) log) for the whole batch."""
    n = len(a[1]) - 1
    hit = np.zeros(n, bool)
    if len(a[0]) > len(b[0]):
        a, b = b, a
    if not len(a[0]) or not len(b[0]):
        return hit
    bits = _bits(a, b)
    sa, ea, row = _runs(a, bits)
    sb, eb, _ = _runs(b, bits)
    first = np.searchsorted(eb, sa, "right")  # the first run that ends after our start
    ok = first < len(sb)
    ok[ok] = sb[first[ok]] < ea[ok]
    hit[row[ok]] = True
    return hit


def probe_overlap(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], at: np.ndarray) -> np.ndarray:
    """Per row of ``a``: does it share an id with list ``at[row]`` of ``b``?  Lists of ``b`` are not copied."""
    hit = np.zeros(len(a[1]) - 1, bool)
    if not len(a[0]) or not len(b[0]):
        return hit
    bits = _bits(b, a)
    row = np.repeat(np.arange(len(a[1]) - 1), np.diff(a[1]) // 2)
    shift = at[row] << (bits + 1)
    sa, ea = a[0][0::2] + shift, a[0][1::2] + shift
    sb, eb, _ = _runs(b, bits)
    first = np.searchsorted(eb, sa, "right")
    ok = first < len(sb)
    ok[ok] = sb[first[ok]] < ea[ok]
    hit[row[ok]] = True
    return hit


def contained(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Per row: does every run of ``a`` lie inside one run of ``b``?  (True for an empty ``a``.)"""
    n = len(a[1]) - 1
    out = np.ones(n, bool)
    if not len(a[0]):
        return out
    bits = _bits(a, b)
    sa, ea, row = _runs(a, bits)
    if not len(b[0]):
        out[row] = False
        return out
    sb, eb, _ = _runs(b, bits)
    at = np.minimum(np.searchsorted(eb, ea, "left"), len(eb) - 1)
    out[row[~((sb[at] <= sa) & (ea <= eb[at]))]] = False
    return out


def probe_contained(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], at: np.ndarray) -> np.ndarray:
    """Per row of ``a``: does every run lie inside one run of list ``at[row]`` of ``b``?"""
    out = np.ones(len(a[1]) - 1, bool)
    if not len(a[0]):
        return out
    bits = _bits(b, a)
    row = np.repeat(np.arange(len(a[1]) - 1), np.diff(a[1]) // 2)
    if not len(b[0]):
        out[row] = False
        return out
    shift = at[row] << (bits + 1)
    sa, ea = a[0][0::2] + shift, a[0][1::2] + shift
    sb, eb, _ = _runs(b, bits)
    k = np.minimum(np.searchsorted(eb, ea, "left"), len(eb) - 1)
    out[row[~((sb[k] <= sa) & (ea <= eb[k]))]] = False
    return out


def unit_runs(cells: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted ids as runs of length one."""
    values, offsets = cells
    return np.stack([values, values + 1], 1).ravel(), offsets * 2


def coarsen(lists: tuple[np.ndarray, np.ndarray], levels: int) -> tuple[np.ndarray, np.ndarray]:
    """Run lists at an order ``levels`` lower: shifted, and merged where they touch or overlap."""
    values, offsets = lists
    if levels <= 0 or not len(values):
        return lists
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets) // 2)
    start, end = values[0::2] >> (2 * levels), ((values[1::2] - 1) >> (2 * levels)) + 1
    new = np.concatenate([[True], (row[1:] != row[:-1]) | (start[1:] > end[:-1])])
    head = np.flatnonzero(new)
    last = np.append(head[1:], len(start)) - 1
    count = np.bincount(row[head], minlength=len(offsets) - 1)
    return np.stack([start[head], end[last]], 1).ravel(), np.concatenate([[0], np.cumsum(2 * count)])


def widen(lists: tuple[np.ndarray, np.ndarray], levels: int) -> tuple[np.ndarray, np.ndarray]:
    """Run lists at an order ``levels`` higher: the same area."""
    return lists[0] << (2 * levels), lists[1]


def overlapping_pairs(a, b, at: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All overlapping run pairs of each row: (run of a, run of b, row), runs by flat number.

    Row i of ``a`` meets list ``at[i]`` of ``b`` (its own number by default).
    """
    if not len(a[0]) or not len(b[0]):
        z = np.zeros(0, np.int64)
        return z, z, z
    bits = _bits(b, a)
    row = np.repeat(np.arange(len(a[1]) - 1), np.diff(a[1]) // 2)
    shift = (row if at is None else at[row]) << (bits + 1)
    sa, ea = a[0][0::2] + shift, a[0][1::2] + shift
    sb, eb, _ = _runs(b, bits)
    lo, hi = np.searchsorted(eb, sa, "right"), np.searchsorted(sb, ea, "left")
    n = np.maximum(hi - lo, 0)
    i = np.repeat(np.arange(len(sa)), n)
    j = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(n.sum())
    return i, j, row[i]
