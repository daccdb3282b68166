"""Box join, filter and exact test as one Arrow stage over tiles: no pair is shuffled or written.

Objects go once to each tile they meet, with their box and geometry.  Within a
tile the larger kind is held and the smaller kind passes in batches; pairs of
meeting boxes are found in chunks, approximations are built for objects that
have a pair, and only verdicts or results leave the stage.  Crowded tiles are
dealt over parts, held objects by HELD and passing ones by PASSING, with the
other kind in each part, so neither memory nor a task is bound to one tile.  A
pair belongs to the tile that holds the lower corner of its common box.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.functions import pairtests
from rasterruns.functions.pairtests import pieces, spread
from rasterruns.grid import DOMAIN
from rasterruns.operators import mbr
from rasterruns.operators.approximate import points
from rasterruns.operators.tiles import BOX, Tiles, uniform_tiles

#: Objects of a tile beyond which the held kind, and the passing kind, are dealt over parts.
HELD, PASSING = 8192, 65_536
#: Objects a tile should hold on average, boxes compared at once, and pairs a kernel gets at once.
PER_TILE, _BOXES, _PAIRS = 2048, 262_144, 65_536

Kernel = Callable[[pa.RecordBatch, pa.RecordBatch, np.ndarray, pa.RecordBatch, np.ndarray], pa.RecordBatch]


def stage_tiles(left: DataFrame, right: DataFrame) -> Tiles:
    """Tiles of level contents, none narrower than twice a mean object of the larger kind, so that few objects are repeated."""
    a, b = mbr.profile(left), mbr.profile(right)
    wanted = math.isqrt(max(a.objects, b.objects) // PER_TILE) + 1
    return uniform_tiles(int(max(1, min(wanted, DOMAIN / max(1.0, a.extent, b.extent)))))


def aligned(rows: Callable | None) -> Callable[[pa.RecordBatch], pa.RecordBatch]:
    """Approximations of a batch in the order of its rows, whatever order ``rows`` builds them in."""

    def build(batch: pa.RecordBatch) -> pa.RecordBatch:
        numbered = pa.RecordBatch.from_arrays([pa.array(np.arange(batch.num_rows)), *(batch.column(c) for c in batch.schema.names if c != "oid")], names=["oid", *(c for c in batch.schema.names if c != "oid")])
        got = pa.Table.from_batches(list(rows(iter([numbered])))).combine_chunks().to_batches()[0]
        return got.take(pa.array(np.argsort(got.column("oid").to_numpy(), kind="stable")))

    return build if rows else lambda batch: batch


def per_pair(kernel: Callable) -> Kernel:
    """A kernel of pair_stage: it gets the small side's columns once a pair."""

    def run(ids, small, i, large, j):
        first, last = int(j.min()), int(j.max()) + 1
        own = pa.RecordBatch.from_arrays([*ids.columns, *(c.take(pa.array(i)) for c in small.columns)], names=[*ids.schema.names, *(f"p_{c}" for c in small.schema.names)])
        table = large.slice(first, last - first)
        return kernel(own, pa.RecordBatch.from_arrays(table.columns, names=[f"q_{c}" for c in table.schema.names]), j - first)

    return run


def _then_exact(kernel: Kernel | None, predicate: str, large: str):
    """The filter, then the exact test of what it leaves; (rid, sid, source) of the results."""
    test = {"intersects": pairtests.intersects, "within": pairtests.within}[predicate]

    def run(ids, small, i, big, j, shapes, big_rings):
        if kernel is None:
            hit, rest = np.zeros(len(i), bool), np.arange(len(i))
        else:
            verdict = kernel(ids, small, i, big, j).column("verdict")
            hit = pc.equal(verdict, "hit").to_numpy(zero_copy_only=False).copy()
            rest = np.flatnonzero(pc.equal(verdict, "unsure").to_numpy(zero_copy_only=False))
        source = np.ones(len(i), np.int8)
        source[hit] = 0
        if len(rest):
            first, last = int(j[rest].min()), int(j[rest].max()) + 1
            hit[rest] = test(shapes, pairtests.Shapes(*points(big_rings.slice(first, last - first))), j[rest] - first, i[rest])
        keep = pa.array(np.flatnonzero(hit))
        names = pa.DictionaryArray.from_arrays(pa.array(source), pa.array(["filter", "exact"])).cast(pa.string())
        return pa.RecordBatch.from_arrays([ids.column("rid").take(keep), ids.column("sid").take(keep), names.take(keep)], names=["rid", "sid", "source"])

    return run


def counted(kernel: Kernel) -> Kernel:
    """(verdict, n) of a chunk instead of its verdicts, so that no pair leaves the stage."""

    def run(ids, small, i, big, j):
        return pa.RecordBatch.from_struct_array(pc.value_counts(kernel(ids, small, i, big, j).column("verdict"))).rename_columns(["verdict", "n"])

    return run


def alternating(column: pa.Array) -> pa.Array:
    """Rings as x, y, x, y ... from lists of all x and then all y."""
    size = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64) // 2
    values = column.flatten().to_numpy()
    start = 2 * (np.cumsum(size) - size)
    row, k = spread(size)
    at = start[row] + k
    out = np.empty(len(values), values.dtype)
    out[0::2], out[1::2] = values[at], values[at + size[row]]
    return pa.ListArray.from_arrays(pa.array(np.append(start, len(values)).astype(np.int32)), pa.array(out))


def _boxes(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([batch.column(c).to_numpy() for c in BOX]).astype(np.int64)


def _meeting(small: np.ndarray, big: np.ndarray, predicate: str, large: str, tiles: Tiles, tile: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Chunks of (small row, large row) whose boxes meet and whose tile this is, by large row."""
    if not small.shape[1] or not big.shape[1]:
        return
    left, bottom = int(small[0].min()), int(small[1].min())
    width, widest, tallest = int(small[0].max()) - left + 2, *(int((small[2 + d] - small[d]).max()) for d in (0, 1))
    step = int((big[3] - big[1]).mean()) // 4 + 1  # strips of the passing objects' lower ends
    strip = (small[1] - bottom) // step
    key = strip * width + small[0] - left
    order = np.argsort(key, kind="stable")
    key, s = key[order], small[:, order]
    first = np.maximum((big[1] - tallest - bottom) // step, 0)
    row, k = spread(np.maximum(np.minimum((big[3] - bottom) // step, strip.max()) - first + 1, 0))
    at = (first[row] + k) * width
    low = np.searchsorted(key, at + np.clip(big[0] - widest - left, 0, width - 1)[row], "left")
    count = np.maximum(np.searchsorted(key, at + np.clip(big[2] - left, -1, width - 1)[row], "right") - low, 0)
    leaf = None if tiles.leaf is None else np.array(tiles.leaf)
    base = lambda v: np.clip(v * tiles.p // DOMAIN, 0, tiles.p - 1)
    for a, b in pieces(count, _BOXES):
        j, k = spread(count[a:b])
        i, j = low[a:b][j] + k, row[a:b][j]
        ok = np.flatnonzero((s[1][i] <= big[3][j]) & (s[3][i] >= big[1][j]))
        i, j = i[ok], j[ok]
        ok = np.flatnonzero((s[2][i] >= big[0][j]) & (s[0][i] <= big[2][j]))
        i, j = i[ok], j[ok]
        if predicate == "within":
            x, y = s[:, i], big[:, j]
            r, t = (y, x) if large == "left" else (x, y)
            ok = np.flatnonzero((r[0] >= t[0]) & (r[2] <= t[2]) & (r[1] >= t[1]) & (r[3] <= t[3]))
            i, j = i[ok], j[ok]
        at = base(np.maximum(s[0][i], big[0][j])) * tiles.p + base(np.maximum(s[1][i], big[1][j]))
        own = np.flatnonzero((at if leaf is None else leaf[at]) == tile)
        i, j = order[i[own]], j[own]
        for c in range(0, len(i), _PAIRS):
            yield i[c : c + _PAIRS], j[c : c + _PAIRS]


def _placed(left: DataFrame, right: DataFrame, tiles: Tiles, large: str, columns: list) -> DataFrame:
    """Both sides' rows by tile and part; kind 0, the held objects, before kind 1."""
    sides = ((left, 0 if large == "left" else 1), (right, 1 if large == "left" else 0))
    rows = [df.select(F.explode(tiles.touched()).alias("tile_id"), F.lit(kind).alias("kind"), "oid", *BOX, *columns) for df, kind in sides]
    ends = [df.select(F.explode(tiles.touched()).alias("tile_id"), F.lit(kind).alias("kind")) for df, kind in sides]
    n = ends[0].unionByName(ends[1]).groupBy("tile_id").agg(F.sum(1 - F.col("kind")).alias("held"), F.sum("kind").alias("passing"))
    n = n.where((F.col("held") > HELD) | (F.col("passing") > PASSING)).select("tile_id", *[F.ceil(F.col(c) / m).cast("int").alias(c) for c, m in (("held", HELD), ("passing", PASSING))])
    both = reduce(DataFrame.unionByName, rows).join(F.broadcast(n), "tile_id", "left")  # at most a row for HELD or PASSING objects
    held, passing = (F.greatest(F.coalesce(F.col(c), F.lit(1)), F.lit(1)) for c in ("held", "passing"))
    mine = F.pmod(F.xxhash64("oid"), F.when(F.col("kind") == 0, held).otherwise(passing)).cast("int")
    parts = F.when(F.col("kind") == 0, F.transform(F.sequence(F.lit(0), passing - 1), lambda k: mine * passing + k)).otherwise(F.transform(F.sequence(F.lit(0), held - 1), lambda k: k * passing + mine))
    both = both.withColumn("part", F.explode(parts)).drop("held", "passing")
    # a fixed number: adaptive planning joins partitions by bytes until a task a core is left, though their pairs differ far more
    spark = left.sparkSession
    tasks = min(int(spark.conf.get("spark.sql.shuffle.partitions")), max(tiles.p**2, spark.sparkContext.defaultParallelism))
    return both.repartition(tasks, "tile_id", "part").sortWithinPartitions("tile_id", "part", "kind")


def box_stage(left: DataFrame, right: DataFrame, boxes: str, builders: tuple, kernel: Kernel | None, schema: str, large: str = "right", tiles: Tiles | None = None, exact: str | None = None, columns: tuple = ()) -> DataFrame:
    """``kernel`` over all pairs of ``left`` and ``right`` whose boxes stand in the relation ``boxes``.

    ``builders``: for the left and the right side the function from batches
    (oid, ring, columns) to approximations, or None.  ``large`` names the kind
    that is held.  ``exact`` adds the exact test of that predicate to what the
    filter leaves unsure (all, without a kernel) and returns results.
    """
    if boxes not in ("intersects", "within"):
        raise ValueError(f"unknown box predicate {boxes}")
    tiles = tiles or stage_tiles(left, right)
    geometry = exact is not None or any(builders)
    # all x, then all y: whole columns of the structs, without a lambda for each vertex
    ring = [F.concat(F.col("ring.x"), F.col("ring.y")).cast("array<int>").alias("ring")] if geometry else []
    extra = [c for c in columns if geometry]
    placed = _placed(left, right, tiles, large, [*ring, *extra])
    build = tuple(aligned(b) for b in (builders if large == "right" else builders[::-1]))  # of the passing, of the held kind
    ids = ("rid", "sid") if large == "right" else ("sid", "rid")
    keep = ["oid", *(["ring"] if geometry else []), *extra]
    final = _then_exact(kernel, exact, large) if exact else lambda *a: kernel(*a[:5])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held, table = None, [], None
        for batch in batches:
            if geometry:
                at = batch.schema.get_field_index("ring")
                batch = batch.set_column(at, "ring", alternating(batch.column(at)))
            tile, part, kind = (batch.column(c).to_numpy() for c in ("tile_id", "part", "kind"))
            new = (tile[1:] != tile[:-1]) | (part[1:] != part[:-1]) | (kind[1:] != kind[:-1])
            cuts = [0, *(np.flatnonzero(new) + 1).tolist(), batch.num_rows]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a == b:
                    continue
                if (tile[a], part[a]) != key:
                    key, held, table = (tile[a], part[a]), [], None
                if kind[a] == 0:
                    held.append(batch.slice(a, b - a))
                    continue
                if not held:
                    continue
                if table is None:
                    rows = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                    table = rows, _boxes(rows), None
                yield from meet(batch.slice(a, b - a), table[0], table[1], int(tile[a]))

    prepared: dict = {}

    def meet(own: pa.RecordBatch, rows: pa.RecordBatch, big: np.ndarray, tile: int) -> Iterator[pa.RecordBatch]:
        small = None
        for i, j in _meeting(_boxes(own), big, boxes, large, tiles, tile):
            if small is None:
                small = build[0](own.select(keep))
                rings = (pairtests.Shapes(*points(own.column("ring"))), rows.column("ring")) if exact else ()
                if prepared.get("rows") is not rows:
                    prepared.clear()
                    prepared.update(rows=rows, large=build[1](rows.select(keep)))
            names = {ids[0]: own.column("oid").take(pa.array(i)), ids[1]: rows.column("oid").take(pa.array(j))}
            found = pa.RecordBatch.from_arrays([pa.array(np.full(len(i), tile, np.int32)), names["rid"], names["sid"]], names=["tile_id", "rid", "sid"])
            yield final(found, small, i, prepared["large"], j, *rings)

    return placed.select("tile_id", "part", "kind", "oid", *BOX, *[c for c in keep if c != "oid"]).mapInArrow(run, "rid long, sid long, source string" if exact else schema)
