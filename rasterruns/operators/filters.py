"""Intermediate filters: verdicts hit, miss or unsure for candidate pairs.

A filter takes pairs with the approximations of both sides attached and is one
Arrow stage; verdicts come out of a projection, so no predicate order is
relied on.  Merges run on the pairs that still need them only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.functions import codec, lists, pairtests
from rasterruns.functions.pairtests import pieces, spread
from rasterruns.operators.approximate import SWAP, points
from rasterruns.operators.pairstage import pair_stage

ORDERS = ("CC,CK,KC", "CC,KC,CK", "CK,KC,CC", "KC,CK,CC", "CK,CC,KC", "KC,CC,CK")
_NAMES = np.array(["unsure", "hit", "miss"])
UNSURE, HIT, MISS = 0, 1, 2
_KEYS = ["tile_id", "rid", "sid"]
_OUT = "tile_id int, rid long, sid long, verdict string, merges int, bytes_decoded long"


def attach(pairs: DataFrame, left: DataFrame, right: DataFrame, columns: list[str], right_columns: list[str] | None = None) -> DataFrame:
    """Pairs with the approximations of both sides (``r_``, ``s_``), fetched by id (and tile)."""
    pairs = pairs if "tile_id" in pairs.columns else pairs.withColumn("tile_id", F.lit(0))
    for side, table, names in (("r", left, columns), ("s", right, right_columns or columns)):
        keys = [F.col("oid").alias(f"{side}id"), *([F.col("tile_id")] if "tile_id" in table.columns else [])]
        picked = table.select(*keys, *[F.col(c).alias(f"{side}_{c}") for c in names])
        # never by broadcast: the planner takes a list column for a few bytes a row
        pairs = pairs.join(picked.hint("merge"), [f"{side}id", *(["tile_id"] if "tile_id" in table.columns else [])])
    return pairs


def _result(batch: pa.RecordBatch, verdict: np.ndarray, merges: np.ndarray | None = None, read: np.ndarray | None = None) -> pa.RecordBatch:
    zero = np.zeros(batch.num_rows, np.int64)
    names = pa.DictionaryArray.from_arrays(pa.array(verdict.astype(np.int8)), pa.array(_NAMES.tolist())).cast(pa.string())
    tail = [names, pa.array((zero if merges is None else merges).astype(np.int32)), pa.array((zero if read is None else read).astype(np.int64))]
    return pa.RecordBatch.from_arrays([*(batch.column(k) for k in _KEYS), *tail], names=[*_KEYS, "verdict", "merges", "bytes_decoded"])


def _each(result):
    """An Arrow stage that applies ``result`` to every batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield result(batch)

    return run


def dual_verdicts(fetch, n: int, order: str = "CC,CK,KC") -> tuple[np.ndarray, np.ndarray]:
    """Verdicts of a batch; ``fetch(side, list, rows)`` gives run lists.  Masks shrink after every merge."""
    verdict, merges = np.full(n, -1), np.zeros(n, np.int64)
    for step in order.split(","):
        rows = np.flatnonzero(verdict < 0)
        if not len(rows):
            break
        a, b = {"CC": ("cover", "cover"), "CK": ("cover", "core"), "KC": ("core", "cover")}[step]
        shared = lists.overlap(fetch("r", a, rows), fetch("s", b, rows))
        merges[rows] += 1
        verdict[rows[~shared] if step == "CC" else rows[shared]] = MISS if step == "CC" else HIT
    verdict[verdict < 0] = UNSURE
    return verdict, merges


def _whole(batch: pa.RecordBatch, read: np.ndarray, mixed: dict[str, int] | None = None):
    """Fetch from plain list columns (8 bytes an end), brought to a common lower order if ``mixed`` says by how much."""
    cache: dict = {}

    def fetch(side: str, name: str, rows: np.ndarray):
        if (side, name) not in cache:
            got = lists.flat(batch.column(f"{side}_{name}"))
            cache[side, name] = lists.coarsen(got, mixed[side]) if mixed else got
        got = lists.take(cache[side, name], rows)
        read[rows] += 8 * np.diff(got[1])
        return got

    return fetch


def _coded(batch: pa.RecordBatch, read: np.ndarray):
    """Fetch from compressed columns: a list is decoded when a merge first needs it."""

    def fetch(side: str, name: str, rows: np.ndarray):
        column = batch.column(f"{side}_{name}").take(pa.array(rows))
        read[rows] += np.array([len(x) for x in column.to_pylist()], np.int64)
        return codec.decode(column)

    return fetch


def _grouped_dual(pairs: DataFrame, left: DataFrame, right: DataFrame, large: str, steps: str, compressed: bool, down: dict[str, int] | None) -> DataFrame:
    """The dual filter with the larger side's lists sent once: they are searched by the runs of the smaller side's."""
    ids = {"left": ("sid", "rid"), "right": ("rid", "sid")}[large]
    tables = [t.select("tile_id", "oid", "cover", "core") for t in ((right, left) if large == "left" else (left, right))]
    return pair_stage(pairs, *tables, *ids, dual_kernel(large, steps, compressed, down), _OUT)


def dual_kernel(large: str, steps: str, compressed: bool = False, down: dict[str, int] | None = None):
    """Verdicts of pairs (``p_`` columns) against rows of large objects (``q_``) by merges in the order of ``steps``."""
    small_side, large_side = ("s", "r") if large == "left" else ("r", "s")

    def kernel(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        n = own.num_rows
        verdict, merges, read = np.full(n, -1), np.zeros(n, np.int64), np.zeros(n, np.int64)
        cache: dict = {}

        def big(name: str):
            if name not in cache:
                got = codec.decode(table.column(f"q_{name}")) if compressed else lists.flat(table.column(f"q_{name}"))
                cache[name] = lists.coarsen(got, down[large_side]) if down else got
            return cache[name]

        def tiny(name: str, rows: np.ndarray):
            column = own.column(f"p_{name}").take(pa.array(rows))
            if compressed:
                read[rows] += np.array([len(x) for x in column.to_pylist()], np.int64)
                return codec.decode(column)
            got = lists.flat(column)
            return lists.coarsen(got, down[small_side]) if down else got

        for step in steps.split(","):
            rows = np.flatnonzero(verdict < 0)
            if not len(rows):
                break
            names = dict(zip("rs", {"CC": ("cover", "cover"), "CK": ("cover", "core"), "KC": ("core", "cover")}[step], strict=True))
            shared = lists.probe_overlap(tiny(names[small_side], rows), big(names[large_side]), at[rows])
            merges[rows] += 1
            verdict[rows[~shared] if step == "CC" else rows[shared]] = MISS if step == "CC" else HIT
        verdict[verdict < 0] = UNSURE
        return _result(own, verdict, merges, read)

    return kernel


def _blockwise_overlap(a: codec.Cursors, b: codec.Cursors, n: int) -> np.ndarray:
    """Merges the coded run lists of many pairs while decoding; a pair stops at its first shared id."""
    hit, live = np.zeros(n, bool), np.arange(n)
    x, y = a.next(live), b.next(live)
    while True:
        some = np.flatnonzero((np.diff(x[1]) > 0) & (np.diff(y[1]) > 0))
        live, x, y = live[some], lists.take(x, some), lists.take(y, some)
        if not len(live):
            return hit
        found = lists.overlap(x, y)
        hit[live[found]] = True
        rest = np.flatnonzero(~found)
        live, x, y = live[rest], lists.take(x, rest), lists.take(y, rest)
        first = x[0][x[1][1:] - 1] <= y[0][y[1][1:] - 1]  # whose block ends first goes on
        x, y = _go_on(a, x, live, first), _go_on(b, y, live, ~first)


def _go_on(cursors: codec.Cursors, held: tuple[np.ndarray, np.ndarray], live: np.ndarray, move: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The next block where ``move`` says so, else the held one."""
    values, offsets = cursors.next(live[move])
    both = np.concatenate([held[0], values]), np.concatenate([held[1], len(held[0]) + offsets[1:]])
    return lists.take(both, np.where(move, len(live) + np.cumsum(move) - 1, np.arange(len(live))))


def incremental_kernel(large: str, steps: str):
    """Verdicts from compressed lists that are decoded block by block inside the merge."""

    def kernel(ids: pa.RecordBatch, small: pa.RecordBatch, i: np.ndarray, big: pa.RecordBatch, j: np.ndarray) -> pa.RecordBatch:
        first, last = int(j.min()), int(j.max()) + 1
        tables = {"r": (big.slice(first, last - first), j - first), "s": (small, i)} if large == "left" else {"r": (small, i), "s": (big.slice(first, last - first), j - first)}
        verdict, merges, read = np.full(len(i), -1), np.zeros(len(i), np.int64), np.zeros(len(i), np.int64)
        for step in steps.split(","):
            rows = np.flatnonzero(verdict < 0)
            if not len(rows):
                break
            names = dict(zip("rs", {"CC": ("cover", "cover"), "CK": ("cover", "core"), "KC": ("core", "cover")}[step], strict=True))
            a, b = (codec.Cursors(tables[x][0].column(names[x]), tables[x][1][rows]) for x in "rs")
            shared = _blockwise_overlap(a, b, len(rows))
            read[rows] += a.read + b.read
            merges[rows] += 1
            verdict[rows[~shared] if step == "CC" else rows[shared]] = MISS if step == "CC" else HIT
        verdict[verdict < 0] = UNSURE
        return _result(ids, verdict, merges, read)

    return kernel


def orders_kernel(large: str):
    """Pairs and merges by verdict for each order of merges: each pair's merges run once, what each order needs of them follows.

    Lists that share no cover cell share none of their cores', so the other two merges run on the rest only.
    """
    small_side, large_side = ("s", "r") if large == "left" else ("r", "s")

    def kernel(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        shared, rows = {}, np.arange(own.num_rows)
        for step, pair in (("CC", ("cover", "cover")), ("CK", ("cover", "core")), ("KC", ("core", "cover"))):
            names = dict(zip("rs", pair, strict=True))
            shared[step] = np.zeros(own.num_rows, bool)
            shared[step][rows] = lists.probe_overlap(lists.flat(own.column(f"p_{names[small_side]}").take(pa.array(rows))), lists.flat(table.column(f"q_{names[large_side]}")), at[rows])
            if step == "CC":
                rows = np.flatnonzero(shared["CC"])
        out = []
        for order in ORDERS:
            verdict, merges = np.full(own.num_rows, -1), np.zeros(own.num_rows, np.int64)
            for step in order.split(","):
                live = verdict < 0
                merges[live] += 1
                verdict[live & (~shared[step] if step == "CC" else shared[step])] = MISS if step == "CC" else HIT
            verdict[verdict < 0] = UNSURE
            n, m = np.bincount(verdict, minlength=3), np.bincount(verdict, weights=merges, minlength=3)
            out += [(order, _NAMES[v], int(n[v]), int(m[v])) for v in range(3) if n[v]]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=["merge_order", "verdict", "n", "merges"])

    return kernel


def merge_steps(merge_order: str, order_left: int | None, order_right: int | None) -> tuple[str, dict[str, int] | None]:
    """The merges to make, and by how many levels each side is shifted down where orders differ."""
    if sorted(merge_order.split(",")) != ["CC", "CK", "KC"]:
        raise ValueError(f"merge order must permute CC, CK and KC: {merge_order}")
    if order_left is None or order_right is None or order_left == order_right:
        return merge_order, None
    low = min(order_left, order_right)
    return ",".join(x for x in merge_order.split(",") if x != ("KC" if order_left > order_right else "CK")), {"r": order_left - low, "s": order_right - low}


def dual_filter(pairs: DataFrame, left: DataFrame, right: DataFrame, merge_order: str = "CC,CK,KC", compressed: bool = False, incremental: bool = False, order_left: int | None = None, order_right: int | None = None, large: str | None = None) -> DataFrame:
    """Intersection filter on dual runs.

    ``large`` (left or right) names the side with the longer lists: these are
    then sent once for all their pairs instead of with every pair.

    With unlike orders the finer side's cover is shifted down, and only the
    merge with the coarser side's core can prove a hit.  ``incremental``
    decodes compressed lists block by block inside the merge and stops early.
    """
    steps, down = merge_steps(merge_order, order_left, order_right)
    if large and not incremental:
        return _grouped_dual(pairs, left, right, large, steps, compressed, down)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, read = batch.num_rows, np.zeros(batch.num_rows, np.int64)
            if compressed and incremental:
                verdict, merges = np.zeros(n, np.int64), np.zeros(n, np.int64)
                columns = {(s, c): batch.column(f"{s}_{c}").to_pylist() for s in "rs" for c in ("cover", "core")}
                for i in range(n):
                    verdict[i] = UNSURE
                    for step in steps.split(","):
                        a, b = {"CC": ("cover", "cover"), "CK": ("cover", "core"), "KC": ("core", "cover")}[step]
                        x, y = codec.Cursor(columns["r", a][i]), codec.Cursor(columns["s", b][i])
                        shared = codec.cursors_overlap(x, y)
                        read[i] += x.read + y.read
                        merges[i] += 1
                        if step == "CC" and not shared or step != "CC" and shared:
                            verdict[i] = MISS if step == "CC" else HIT
                            break
            else:
                verdict, merges = dual_verdicts(_coded(batch, read) if compressed else _whole(batch, read, down), n, steps)
            yield _result(batch, verdict, merges, read)

    return attach(pairs, left, right, ["cover", "core"]).mapInArrow(run, _OUT)


def dual_within_filter(pairs: DataFrame, left: DataFrame, right: DataFrame, strict: bool = False, order_left: int | None = None, order_right: int | None = None) -> DataFrame:
    """Is r within s?  No shared cell: miss; all of r's cells in s's core: hit.

    ``strict`` (ours) adds: a cell of r outside s's cover is a miss.  With
    unlike orders the finer cover is shifted down, or the coarser one widened;
    the first may only prove hits and misses of the cells themselves.
    """
    # the container has the longer lists
    return pair_stage(pairs, left.select("tile_id", "oid", "cover"), right.select("tile_id", "oid", "cover", "core"), "rid", "sid", within_kernel(strict, order_left, order_right), _OUT)


def within_kernel(strict: bool = False, order_left: int | None = None, order_right: int | None = None):
    up = down = 0
    if order_left is not None and order_right is not None:
        down, up = max(0, order_left - order_right), max(0, order_right - order_left)

    def kernel(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        r = lists.widen(lists.coarsen(lists.flat(own.column("p_cover")), down), up)
        s, k = (lists.flat(table.column(c)) for c in ("q_cover", "q_core"))
        verdict = np.full(own.num_rows, UNSURE)
        verdict[lists.probe_contained(r, k, at)] = HIT
        verdict[~lists.probe_overlap(r, s, at)] = MISS
        if strict and not up:
            verdict[~lists.probe_contained(r, s, at)] = MISS
        return _result(own, verdict)

    return kernel


#: Cells whose codes are compared in one step: 3 bits each, 57 of a word's 64, so that any shift within a byte fits.
WORD_CELLS = 19
_ONES = np.uint64((8**WORD_CELLS - 1) // 7)  # the lowest bit of every code
_WORD = np.uint64(8**WORD_CELLS - 1)


#: Beyond all ids of a grid (of order 20 at most): keeps the lists of different rows apart.
_STRIDE = 1 << 41


def _run_lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Runs of a column, compressed or not."""
    return codec.decode(column) if pa.types.is_binary(column.type) else lists.flat(column)


class Coded:
    """Coded runs of a table's rows, decoded once: runs, and the eight bytes of codes from each byte on."""

    def __init__(self, runs: pa.Array, codes: pa.Array):
        self.lists = _run_lists(runs)
        values, self.off = self.lists[0], self.lists[1] // 2
        self.start, self.end = values[0::2], values[1::2]
        codes = codec.inflate(codes) if pa.types.is_binary(runs.type) else codes
        data = np.frombuffer(b"".join(codes.to_pylist()) + bytes(8), np.uint8)
        self.words = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(data, 8)).view(">u8").ravel().astype(np.uint64)
        self.byte = np.concatenate([[0], np.cumsum((3 * (self.end - self.start) + 7) // 8)])
        if len(values) and int(values.max()) >= _STRIDE or len(self.off) > 1 << 20:
            raise ValueError("ids too wide for one batch; lower the batch size")
        row = np.repeat(np.arange(len(self.off) - 1), np.diff(self.off))
        self.starts, self.ends = self.start + row * _STRIDE, self.end + row * _STRIDE

    def codes(self, run: np.ndarray, first: np.ndarray) -> np.ndarray:
        """The codes of WORD_CELLS cells from cell ``first`` of each run on."""
        bit = 8 * self.byte[run] + 3 * (first - self.start[run])
        return (self.words[bit >> 3] << (bit & 7).astype(np.uint64)) >> np.uint64(7)


def coded_words(a: Coded, b: Coded, i: np.ndarray, j: np.ndarray, at_once: int = 131_072):
    """Aligned codes of the stretches that row ``i`` of a and row ``j`` of b both hold, up to WORD_CELLS cells a word.

    Yields (pair of each word, a's words, b's words, the bits in use).
    """
    count = np.diff(a.off)[i]
    for p, q in pieces(count, at_once):
        row, k = spread(count[p:q])
        row += p
        run, shift = a.off[:-1][i[row]] + k, j[row] * _STRIDE
        low, high = np.searchsorted(b.ends, a.start[run] + shift, "right"), np.searchsorted(b.starts, a.end[run] + shift, "left")
        n = np.maximum(high - low, 0)
        mine, k = spread(n)
        own, run, other = row[mine], run[mine], low[mine] + k
        start = np.maximum(a.start[run], b.start[other])
        size = np.minimum(a.end[run], b.end[other]) - start
        for c, d in pieces((size + WORD_CELLS - 1) // WORD_CELLS, at_once):
            word, k = spread((size[c:d] + WORD_CELLS - 1) // WORD_CELLS)
            word += c
            first = start[word] + WORD_CELLS * k
            unused = (3 * np.maximum(WORD_CELLS * (k + 1) - size[word], 0)).astype(np.uint64)
            used = _WORD >> unused << unused
            yield own[word], a.codes(run[word], first) & used, b.codes(other[word], first) & used, used


def common_words(a: tuple[pa.Array, pa.Array], b: tuple[pa.Array, pa.Array], at: np.ndarray | None = None, at_once: int = 131_072):
    """``coded_words`` of columns of runs and codes, compressed or not; row i of ``a`` meets row ``at[i]`` of ``b`` (its own number by default)."""
    i = np.arange(len(a[0]))
    return coded_words(Coded(*a), Coded(*b), i, i if at is None else at, at_once)


def coded_filter(pairs: DataFrame, left: DataFrame, right: DataFrame, same_side: bool = False, large: str = "right") -> DataFrame:
    """Intersection filter on coded runs: a common cell whose codes share a bit proves a hit.

    ``same_side``: both lists carry left-hand codes; one side's are swapped on
    the way.  ``large`` names the side whose lists are sent once.
    """
    sides = (right, left, "sid", "rid") if large == "left" else (left, right, "rid", "sid")
    return pair_stage(pairs, *(t.select("oid", "runs", "code") for t in sides[:2]), *sides[2:], _of_pairs(coded_kernel(same_side)), _OUT)


def _of_pairs(kernel):
    """A kernel on coded runs for pair_stage, whose pairs carry the small side's columns."""

    def run(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        names = ["runs", "code"]
        small, big = (pa.RecordBatch.from_arrays([t.column(f"{p}_{c}") for c in names], names=names) for t, p in ((own, "p"), (table, "q")))
        return kernel(own, small, np.arange(own.num_rows), big, at)

    return run


def coded_kernel(same_side: bool = False):
    """The coded filter for pairs of table rows: lists are decoded once an object, not once a pair."""
    swap = np.uint64(SWAP) * _ONES
    read = _kept(lambda table: Coded(table.column("runs"), table.column("code")))

    def kernel(ids: pa.RecordBatch, small: pa.RecordBatch, i: np.ndarray, big: pa.RecordBatch, j: np.ndarray) -> pa.RecordBatch:
        hit, some = np.zeros(len(i), bool), np.zeros(len(i), bool)
        for row, p, q, used in coded_words(read(small, "small"), read(big, "big"), i, j):
            some[row] = True
            hit[row[(p & ((q ^ swap) & used if same_side else q)) != 0]] = True
        return _result(ids, np.where(hit, HIT, np.where(some, UNSURE, MISS)))

    return kernel


def coded_within_filter(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Is r within s, on coded runs (left-hand codes on r, right-hand on s)?  s's lists are sent once.

    Types are read off a word's bits: a left-hand code lacks its first bit when
    full and has the last one too when strong; a right-hand code lacks its
    middle bit when full and the last one when weak.
    """
    return pair_stage(pairs, left.select("oid", "runs", "code"), right.select("oid", "runs", "code"), "rid", "sid", _of_pairs(coded_within_kernel()), _OUT)


def coded_within_kernel():
    one, two = np.uint64(1), np.uint64(2)
    read = _kept(lambda table: Coded(table.column("runs"), table.column("code")))

    def kernel(ids: pa.RecordBatch, small: pa.RecordBatch, i: np.ndarray, big: pa.RecordBatch, j: np.ndarray) -> pa.RecordBatch:
        a, b = read(small, "small"), read(big, "big")
        miss = ~lists.probe_contained(lists.take(a.lists, i), b.lists, j)
        full = np.ones(len(i), bool)
        for row, p, q, used in coded_words(a, b, i, j):
            here = used & _ONES
            partly = (q >> one) & here
            less = (~(p >> two) & here & partly) | ((p >> two) & p & partly & ~q)
            miss[row[less != 0]] = True
            full[row[partly != 0]] = False
        return _result(ids, np.where(miss, MISS, np.where(full, HIT, UNSURE)))

    return kernel


def upscale(pair: np.ndarray, cx: np.ndarray, cy: np.ndarray, kind: np.ndarray, levels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells at a coarser level by pair: (key, type).

    All children full: full; a proven share above one half: strong; else weak.
    """
    key = (pair << 42) | ((cx >> levels) << 21) | (cy >> levels)
    if not len(key):
        return key, kind
    n, full, strong = 1 << (2 * levels), kind == 3, kind == 2
    order = slice(None)
    for _ in range(2):  # cells along the curve stand beside their siblings, so only one row a coarse cell is left to sort
        key, n, full, strong = (v[order] for v in (key, n, full, strong))
        head = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        key, n, full, strong = key[head], n[head], np.add.reduceat(full, head, dtype=np.int64), np.add.reduceat(strong, head, dtype=np.int64)
        order = np.argsort(key, kind="stable")
    above = (2 * full + strong > n) | ((2 * full + strong == n) & (strong > 0))
    return key, np.where(full == n, 3, np.where(above, 2, 1))


def _aligned(batch: pa.RecordBatch):
    """Types of both sides' cells on each pair's coarser grid, and by how much each side was scaled."""
    level = {s: batch.column(f"{s}_k").to_numpy().astype(np.int64) for s in "rs"}
    top = np.maximum(level["r"], level["s"])
    out = {}
    for s in "rs":
        column = batch.column(f"{s}_cells")
        size = column.value_lengths().to_numpy()
        pair = np.repeat(np.arange(batch.num_rows), size)
        f = column.flatten()
        x, y, t = (f.field(c).to_numpy().astype(np.int64) for c in ("cx", "cy", "type"))
        out[s] = upscale(pair, x, y, t, (top - level[s])[pair])
    return out["r"], out["s"], top - level["s"]


def local_raster_filter(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Intersection filter on local rasters: the finer one is scaled to the coarser one's cells."""
    return attach(pairs, left, right, ["k", "cells"]).mapInArrow(_each(raster_result), _OUT)


def raster_result(batch: pa.RecordBatch) -> pa.RecordBatch:
    (rk, rt), (sk, st), _ = _aligned(batch)
    _, i, j = np.intersect1d(rk, sk, assume_unique=True, return_indices=True)
    pair = rk[i] >> 42
    verdict = np.full(batch.num_rows, MISS)
    verdict[pair] = UNSURE
    sure = (rt[i] == 3) | (st[j] == 3) | ((rt[i] == 2) & (st[j] == 2))
    verdict[pair[sure]] = HIT
    return _result(batch, verdict)


def local_raster_within(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Is r within s, on local rasters?  Only the rules that scaling keeps sound."""
    return attach(pairs, left, right, ["k", "cells"]).mapInArrow(_each(raster_within_result), _OUT)


def raster_within_result(batch: pa.RecordBatch) -> pa.RecordBatch:
    (rk, rt), (sk, st), scaled = _aligned(batch)
    at = np.minimum(np.searchsorted(sk, rk), max(len(sk) - 1, 0))
    here = sk[at] == rk if len(sk) else np.zeros(len(rk), bool)
    other = np.where(here, st[at] if len(sk) else 0, 0)
    pair = rk >> 42
    miss = (other == 0) | ((rt == 3) & (other != 3)) | ((rt == 2) & (other == 1) & (scaled[pair] == 0))
    verdict = np.full(batch.num_rows, HIT)
    verdict[pair[other != 3]] = UNSURE
    verdict[pair[miss]] = MISS
    return _result(batch, verdict)


#: By type: halves, strong, not empty (see Windows), and cells of windows handled at once.
_SUM = np.array([0, 1, 1 << 8 | 1 << 4 | 1, 2 << 8 | 1])
_CELLS = 65_536


class Windows:
    """Local rasters of a table as codes by window, with coarser copies made as they are asked for.

    ``place`` has (x0, y0, x1, y1, width, first cell) of each raster: the
    table's own, then the coarser ones; ``entry`` finds them by row and level.
    Stored windows begin at even cells and have even sides, empty cells added,
    so that two cells with one parent in a row stand at 2 i and 2 i + 1.

    ``sums`` holds for each two such cells what they add to their parent: halves
    (full cells two, strong ones one) above two counters of four bits, of
    strong cells and of cells that aren't empty.
    """

    def __init__(self, table: pa.RecordBatch, codes: np.ndarray):
        self.k = table.column("k").to_numpy().astype(np.int64)
        x0, y0, w, h = (table.column(c).to_numpy() for c in ("x0", "y0", "w", "h"))
        column = table.column("types")
        off = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
        types = np.frombuffer(column.buffers()[2], np.uint8)
        self.unit = _SUM.astype(np.int32 if not len(w) or int((w * h).max()) < 1 << 20 else np.int64)
        self.entry = np.full((len(w), 32), -1)
        self.entry[np.arange(len(w)), self.k] = np.arange(len(w))
        self.code_of, self.used = codes, 0
        self.place, self.codes, self.sums = np.zeros((0, 6), np.int64), np.zeros(0, np.uint8), np.zeros(0, self.unit.dtype)
        place, size = self._even(x0, y0, x0 + w - 1, y0 + h - 1)
        cells = np.zeros(int(size.sum()), np.uint8)
        for a, b in pieces(w * h, _CELLS):
            line, r = spread(h[a:b])
            line += a
            n = w[line]
            at = np.arange(int(n.sum())) + np.repeat(place[line, 5] + r * place[line, 4] - (np.cumsum(n) - n), n)
            cells[at] = types[off[a] : off[b]]
        self._add(place, cells, self.unit[cells])

    def _even(self, x0, y0, x1, y1) -> tuple[np.ndarray, np.ndarray]:
        """Places of new rasters behind those there are, and what each takes."""
        width = (x1 | 1) - (x0 & -2) + 1
        size = width * ((y1 | 1) - (y0 & -2) + 1)
        return np.stack([x0, y0, x1, y1, width, self.used + np.cumsum(size) - size + (y0 & 1) * width + (x0 & 1)], 1), size

    def _add(self, place: np.ndarray, types: np.ndarray, sums: np.ndarray) -> None:
        self.place = np.concatenate([self.place, place])
        end = self.used + len(types)
        if end > len(self.codes):  # room for as much again
            self.codes, self.sums = (np.concatenate([v[: self.used // c], np.empty((2 * end - self.used) // c, v.dtype)]) for v, c in ((self.codes, 1), (self.sums, 2)))
        np.take(self.code_of, types, out=self.codes[self.used : end], mode="clip")
        np.add(sums[0::2], sums[1::2], out=self.sums[self.used // 2 : end // 2])
        self.used = end

    def at(self, rows: np.ndarray, level: np.ndarray) -> np.ndarray:
        """Places of the rasters of ``rows`` at levels not below their own."""
        got = self.entry[rows, level]
        missing = np.flatnonzero(got < 0)
        if len(missing):
            want = np.zeros(self.entry.shape, bool)
            want[rows[missing], level[missing]] = True
            for t in range(31, 0, -1):  # a raster is made from the one a level finer
                want[:, t - 1] |= want[:, t] & (self.entry[:, t - 1] < 0)
            for t in np.flatnonzero(want.any(0)).tolist():
                self._coarsen(np.flatnonzero(want[:, t]), t)
            got = self.entry[rows, level]
        return got

    def _coarsen(self, rows: np.ndarray, t: int) -> None:
        """Rasters of ``rows`` at level ``t``: all children full: full; a proven share above one half: strong; else weak."""
        x0, y0, x1, y1, width, start = self.place[self.entry[rows, t - 1]].T
        start = (start - (y0 & 1) * width - (x0 & 1)) >> 1  # of the window's first sum
        width = width >> 1
        x0, y0, x1, y1 = x0 >> 1, y0 >> 1, x1 >> 1, y1 >> 1
        place, size = self._even(x0, y0, x1, y1)
        high = y1 - y0 + 1
        types, sums = np.zeros(int(size.sum()), np.uint8), np.zeros(int(size.sum()), self.sums.dtype)
        for a, b in pieces(width * high, _CELLS):
            line, r = spread(high[a:b])
            line += a
            n = width[line]
            before = np.cumsum(n) - n
            k = np.arange(int(n.sum()))
            source = k + np.repeat(start[line] + 2 * r * n - before, n)
            got = self.sums[source] + self.sums[source + np.repeat(n, n)]
            halves, strong, some = got >> 8, got & 0xF0, got & 0xF
            all_ = np.repeat((1 << 2 * (t - self.k[rows])).astype(got.dtype)[line], n)
            target = k + np.repeat(place[line, 5] - self.used + r * place[line, 4] - before, n)
            some, strong = some > 0, strong > 0
            above = (halves > all_) | ((halves == all_) & strong)
            types[target] = some.astype(np.uint8) + above + (halves == 2 * all_)
            sums[target] = halves << 8 | strong.astype(got.dtype) << 4 | some
        self.entry[rows, t] = len(self.place) + np.arange(len(rows))
        self._add(place, types, sums)


#: By type, for the passing and the held side: bits of which a cell's common ones tell what it proves.
#: intersects: 1 both not empty, others a sure hit; within: 1 and 4 a sure miss, 8 one if the held side wasn't scaled, 2 not proven.
_BITS = {
    "intersects": (np.array([0, 9, 11, 15], np.uint8), np.array([0, 5, 7, 15], np.uint8)),
    "within": (np.array([0, 3, 11, 7], np.uint8), np.array([7, 14, 6, 0], np.uint8)),
}


def raster_kernel(predicate: str):
    """The local raster filters for pairs of table rows: objects are scaled once a level, not once a pair.

    Both rasters stand in windows of one grid, so their common cells are
    compared in place; for ``within`` the passing side is the inner one.
    """
    passing, holding = _BITS[predicate]
    small_of, large_of = _kept(lambda table: Windows(table, passing)), _kept(lambda table: Windows(table, holding))

    def kernel(ids: pa.RecordBatch, small: pa.RecordBatch, i: np.ndarray, large: pa.RecordBatch, j: np.ndarray) -> pa.RecordBatch:
        r, s = small_of(small, "small"), large_of(large, "large")
        top = np.maximum(r.k[i], s.k[j])
        at = r.at(i, top), s.at(j, top)
        p, q = r.place[at[0]].T, s.place[at[1]].T
        left, bottom = np.maximum(p[0], q[0]), np.maximum(p[1], q[1])
        wide, high = np.maximum(np.minimum(p[2], q[2]) - left + 1, 0), np.maximum(np.minimum(p[3], q[3]) - bottom + 1, 0)
        high[wide == 0] = 0
        size = wide * high
        first = [v[5] + (bottom - v[1]) * v[4] + left - v[0] for v in (p, q)]
        shared = np.zeros(len(i), np.uint8)
        for c, d in pieces(size, _CELLS):
            line, k = spread(high[c:d])
            line += c
            n = wide[line]
            cells = np.cumsum(n)
            at = np.arange(int(cells[-1]) if len(cells) else 0)
            both = [v.codes[at + np.repeat(f[line] + k * w[4][line] - (cells - n), n)] for v, f, w in ((r, first[0], p), (s, first[1], q))]
            some = np.flatnonzero(size[c:d])
            if len(some):
                shared[c + some] = np.bitwise_or.reduceat(both[0] & both[1], (np.cumsum(size[c:d]) - size[c:d])[some])
        if predicate == "intersects":
            return _result(ids, np.where(shared > 1, HIT, np.where(shared > 0, UNSURE, MISS)))
        out = (p[0] < q[0]) | (p[1] < q[1]) | (p[2] > q[2]) | (p[3] > q[3])  # a window's outer rows and columns aren't empty
        miss = out | (shared & 5 > 0) | ((shared & 8 > 0) & (s.k[j] == top))
        return _result(ids, np.where(miss, MISS, np.where(shared > 0, UNSURE, HIT)))

    return kernel


def corner_hull_filter(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Five corners apart, or else hulls apart: miss; never a hit.  Serves polygons and lines alike."""
    return attach(pairs, left, right, ["corners", "hull"]).mapInArrow(_each(hull_result), _OUT)


def hull_result(batch: pa.RecordBatch) -> pa.RecordBatch:
    apart = np.zeros(batch.num_rows, bool)
    for kind in ("corners", "hull"):  # hulls are compared where the corners leave it open
        rest = np.flatnonzero(~apart)
        a, b = (pairtests.Convex.read(batch.column(f"{side}_{kind}").take(pa.array(rest))) for side in "rs")
        apart[rest] = pairtests.convex_apart(a, b)
    return _result(batch, np.where(apart, MISS, UNSURE))


def hull_kernel(predicate: str, large: str):
    """The corner and hull filters for pairs of table rows: corners and hulls are read once an object, not once a pair.

    Hulls that surely share a point, a corner of the passing one, are not apart;
    neither are their corners' polygons, which hold them.  Hulls are apart where
    the box of one lies beside all sides of the other that reach its heights.
    """
    read = _kept(lambda table: {c: pairtests.Convex.read(table.column(c)) for c in ("corners", "hull")} | {"sides": pairtests.Shapes(*points(table.column("hull")))})

    def kernel(ids: pa.RecordBatch, small: pa.RecordBatch, i: np.ndarray, big: pa.RecordBatch, j: np.ndarray) -> pa.RecordBatch:
        a, b = read(small, "small"), read(big, "big")
        if predicate == "within":
            inner, p, outer, q = (b, j, a, i) if large == "left" else (a, i, b, j)
            miss = np.zeros(len(i), bool)
        else:
            miss, rest = pairtests.hulls_settled(a["sides"], b["sides"], i, j)
        for kind in ("corners", "hull"):
            if predicate == "within":
                left = np.flatnonzero(~miss)
                miss[left] = pairtests.convex_sticks_out(inner["hull"], outer[kind], p[left], q[left])
            else:
                left = rest[~miss[rest]]
                miss[left] = pairtests.convex_apart(a[kind], b[kind], i[left], j[left])
        return _result(ids, np.where(miss, MISS, UNSURE))

    return kernel


def _kept(make):
    """``make`` of a table, kept while the same table is asked for under the same name."""
    kept: dict = {}

    def get(table: pa.RecordBatch, name: str):
        if name not in kept or kept[name][0] is not table:
            kept[name] = table, make(table)
        return kept[name][1]

    return get


def corner_hull_within(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """r's hull sticks out of s's five corners or hull: miss; never a hit."""
    return attach(pairs, left, right, ["hull"], ["corners", "hull"]).mapInArrow(_each(hull_within_result), _OUT)


def hull_within_result(batch: pa.RecordBatch) -> pa.RecordBatch:
    out = np.zeros(batch.num_rows, bool)
    for kind in ("corners", "hull"):
        rest = np.flatnonzero(~out)
        a, b = (pairtests.Convex.read(batch.column(c).take(pa.array(rest))) for c in ("r_hull", f"s_{kind}"))
        out[rest] = pairtests.convex_sticks_out(a, b)
    return _result(batch, np.where(out, MISS, UNSURE))


def dual_line_filter(pairs: DataFrame, polygons: DataFrame, lines: DataFrame) -> DataFrame:
    """Does a path (its cells) meet a polygon (its dual runs)?  The polygon's lists are sent once."""

    def kernel(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        cells = lists.unit_runs(lists.flat(own.column("p_cells")))
        verdict = np.full(own.num_rows, UNSURE)
        verdict[lists.probe_overlap(cells, lists.flat(table.column("q_core")), at)] = HIT
        verdict[~lists.probe_overlap(cells, lists.flat(table.column("q_cover")), at)] = MISS
        return _result(own, verdict)

    return pair_stage(pairs, lines.select("oid", "cells"), polygons.select("tile_id", "oid", "cover", "core"), "sid", "rid", kernel, _OUT)


def no_filter(pairs: DataFrame) -> DataFrame:
    """The direct method: every pair stays unsure."""
    pairs = pairs if "tile_id" in pairs.columns else pairs.withColumn("tile_id", F.lit(0))
    return pairs.select("tile_id", "rid", "sid", F.lit("unsure").alias("verdict"), F.lit(0).alias("merges"), F.lit(0).cast("long").alias("bytes_decoded"))


def unsure_kernel(ids: pa.RecordBatch, *_) -> pa.RecordBatch:
    return _result(ids, np.full(ids.num_rows, UNSURE))


def aligned_and(a: bytes, b: bytes, shift: int, bits: int, swap: bool = False) -> bool:
    """Do two code strings share a set bit, ``a`` entered ``shift`` bits in, over ``bits`` bits?  (One pair, in integers.)"""
    x = int.from_bytes(a, "big") >> max(0, 8 * len(a) - shift - bits)
    y = int.from_bytes(b, "big") >> max(0, 8 * len(b) - bits)
    if swap:
        y ^= int("110" * (bits // 3), 2)
    return bool(x & y & ((1 << bits) - 1))
