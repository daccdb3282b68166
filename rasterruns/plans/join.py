"""Three-stage plans: box join, intermediate filter, exact test on what is left."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rasterruns.functions import lists
from rasterruns.grid import DOMAIN, GridSpec
from rasterruns.operators import approximate, boxstage, filters, mbr, rasterize
from rasterruns.operators.refine import refine
from rasterruns.operators.tiles import Tiles, assign, raster_boxes, uniform_tiles
from rasterruns.runtime import materialize

METHODS = ("dual", "dual_compressed", "coded", "coded_compressed", "local_raster", "corner_hull", "direct")
#: The method guesses of merge_order="auto": proving a hit first pays where boxes are of unlike size.
AUTO_RATIO = 64


@dataclass
class JoinResult:
    """``pairs(rid, sid, source)``: the result, by filter or by exact test; ``verdicts``: all candidates.

    ``counts(verdict, n)``, where the stage over tiles counts them itself.
    """

    pairs: DataFrame
    verdicts: DataFrame
    counts: DataFrame | None = None

    def stats(self) -> DataFrame:
        """Candidates by verdict, with the share in basis points."""
        if self.counts is None:
            n = self.verdicts.groupBy("verdict").agg(F.count(F.lit(1)).alias("n"))
        else:
            n = self.counts.groupBy("verdict").agg(F.sum("n").alias("n"))
        total = F.sum("n").over(Window.partitionBy(F.lit(0)))  # over one row a verdict
        return n.select("verdict", "n", F.floor(F.col("n") * 10000 / total).cast("long").alias("bp"))


def approximate_layer(layer: DataFrame, method: str, side: str, grid: GridSpec, construction: str = "onestep_neighbours", max_cells: int = 750, column: str = "ring") -> DataFrame | None:
    """The approximation of a layer that a method needs."""
    if method in ("dual", "dual_compressed"):
        return approximate.build_dual(layer, grid, construction, compressed=method == "dual_compressed")
    if method in ("coded", "coded_compressed"):
        return approximate.build_coded(layer, grid, side, compressed=method == "coded_compressed")
    if method == "local_raster":
        return approximate.build_local_raster(layer, max_cells)
    if method == "corner_hull":
        return approximate.build_corner_hull(layer, column)
    if method == "direct":
        return None
    raise ValueError(f"unknown method {method}")


def larger_side(left: DataFrame, right: DataFrame) -> str:
    """The side whose objects have the longer boundaries on average."""
    return "left" if mbr.profile(left).extent > mbr.profile(right).extent else "right"


def guess_order(left: DataFrame, right: DataFrame) -> str:
    """A merge order from mean box areas; ours, off by default."""
    r, s = mbr.profile(left).area, mbr.profile(right).area
    return "CK,KC,CC" if s > AUTO_RATIO * r else "KC,CK,CC" if r > AUTO_RATIO * s else "CC,CK,KC"


def verdicts(pairs: DataFrame, left: DataFrame, right: DataFrame, predicate: str = "intersects", method: str = "dual", grid: GridSpec = GridSpec(), merge_order: str = "CC,CK,KC", approx: tuple | None = None, order_left: int | None = None, order_right: int | None = None, strict: bool = False, max_cells: int = 750) -> DataFrame:
    """Filter candidate pairs by a method; ``approx`` gives stored approximations instead of building them."""
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    if predicate == "line" and method in ("coded", "coded_compressed", "local_raster"):
        raise ValueError(f"{method} isn't offered for lines: a strong cell proves nothing about a path")
    if method == "direct":
        return filters.no_filter(pairs)
    if merge_order == "auto":
        merge_order = guess_order(left, right)
    if predicate == "line" and method.startswith("dual"):
        a, b = approx or (approximate.build_dual(left, grid), approximate.build_line_cells(right, grid))
        return filters.dual_line_filter(pairs, a, b)
    if approx is None:
        grids = [GridSpec(o) if o else grid for o in (order_left, order_right)]
        a = approximate_layer(left, method, "R", grids[0], max_cells=max_cells)
        b = approximate_layer(right, method, "S", grids[1], max_cells=max_cells, column="path" if predicate == "line" else "ring")
    else:
        a, b = approx
    if predicate == "within":
        if method == "dual_compressed":
            a, b = approximate.decompress(a), approximate.decompress(b)
        if method.startswith("dual"):
            return filters.dual_within_filter(pairs, a, b, strict, order_left, order_right)
        return {"coded": filters.coded_within_filter, "coded_compressed": filters.coded_within_filter, "local_raster": filters.local_raster_within, "corner_hull": filters.corner_hull_within}[method](pairs, a, b)
    if method.startswith("dual"):
        return filters.dual_filter(pairs, a, b, merge_order, method == "dual_compressed", order_left=order_left, order_right=order_right, large=larger_side(left, right))
    if method.startswith("coded"):
        return filters.coded_filter(pairs, a, b, large=larger_side(left, right))
    return {"local_raster": filters.local_raster_filter, "corner_hull": filters.corner_hull_filter}[method](pairs, a, b)


def box_verdicts(left: DataFrame, right: DataFrame, predicate: str = "intersects", method: str = "dual", grid: GridSpec = GridSpec(), boxes: str = "intersects", tiles: Tiles | None = None, exact: bool = False, merge_order: str = "CC,CK,KC", order_left: int | None = None, order_right: int | None = None, strict: bool = False, max_cells: int = 750, incremental: bool = False, counts: bool = False) -> DataFrame:
    """Box join and filter in one stage over tiles (polygons only); with ``exact`` the exact test too, giving (rid, sid, source).

    ``counts`` gives (verdict, n) instead of a row for each pair; a verdict has many rows.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    if predicate not in ("intersects", "within"):
        raise ValueError(f"the stage over tiles has no predicate {predicate}")
    within = predicate == "within"
    large = "right" if within else larger_side(left, right)
    tiles = tiles or boxstage.stage_tiles(left, right)  # before columns are added: the frames keep their profiles
    if merge_order == "auto":
        merge_order = guess_order(left, right)
    grids = [GridSpec(o) if o else grid for o in (order_left, order_right)]
    columns: tuple = ()
    builders, kernel = (None, None), None
    if method.startswith("dual"):
        packed = method == "dual_compressed" and not within
        builders = tuple(approximate.dual_rows(g, compressed=packed) for g in grids)
        steps, down = filters.merge_steps(merge_order, order_left, order_right)
        if incremental:
            if not packed or down:
                raise ValueError("block by block, only compressed lists of one order are merged")
            kernel = filters.incremental_kernel(large, steps)
        else:
            kernel = boxstage.per_pair(filters.within_kernel(strict, order_left, order_right) if within else filters.dual_kernel(large, steps, packed, down))
    elif method.startswith("coded"):
        builders = tuple(approximate.coded_rows(g, side, compressed=method == "coded_compressed") for g, side in zip(grids, "RS", strict=True))
        kernel = filters.coded_within_kernel() if within else filters.coded_kernel()
    elif method == "local_raster":
        left, right = (approximate.raster_level(x, max_cells) for x in (left, right))
        builders, columns, kernel = (approximate.raster_rows(windows=True), approximate.raster_rows(windows=True)), ("k",), filters.raster_kernel(predicate)
    elif method == "corner_hull":
        builders, kernel = (approximate.hull_rows, approximate.hull_rows), filters.hull_kernel(predicate, large)
    elif not exact:
        kernel = filters.unsure_kernel
    if counts:
        kernel = boxstage.counted(kernel)
    return boxstage.box_stage(left, right, boxes, builders, kernel, "verdict string, n long" if counts else filters._OUT, large, tiles, predicate if exact else None, columns)


def order_counts(left: DataFrame, right: DataFrame, grid: GridSpec = GridSpec()) -> DataFrame:
    """``(merge_order, verdict, n, merges)`` of the dual filter in all orders of merges, in one stage."""
    large = larger_side(left, right)
    rows = approximate.dual_rows(grid)
    got = boxstage.box_stage(left, right, "intersects", (rows, rows), boxstage.per_pair(filters.orders_kernel(large)), "merge_order string, verdict string, n long, merges long", large)
    return got.groupBy("merge_order", "verdict").agg(F.sum("n").alias("n"), F.sum("merges").alias("merges"))


def finish(found: DataFrame, left: DataFrame, right: DataFrame, predicate: str) -> JoinResult:
    """Hits as they are, unsure pairs by the exact test.

    Verdicts are cut at files first: the filter runs once though two branches
    read it, and a failed exact test doesn't repeat it.
    """
    found = materialize(found)
    hits = found.where("verdict = 'hit'").select("rid", "sid", F.lit("filter").alias("source"))
    large = larger_side(left, right) if predicate == "intersects" else None
    rest = refine(found.where("verdict = 'unsure'"), left, right, predicate, large).withColumn("source", F.lit("exact"))
    return JoinResult(hits.unionByName(rest), found)


def spatial_join(left: DataFrame, right: DataFrame, predicate: str = "intersects", method: str = "dual", grid: GridSpec = GridSpec(), tiles: Tiles | None = None, mbr_predicate: str | None = None, strategy: str = "tiled", **options) -> JoinResult:
    """Join two layers.  ``predicate``: intersects, within (left within right) or line (polygons left, paths right)."""
    boxes = mbr_predicate or ("within" if predicate == "within" else "intersects")
    if predicate != "line" and strategy == "tiled" and options.get("approx") is None:
        options.pop("approx", None)
        both = [box_verdicts(left, right, predicate, method, grid, boxes, tiles, exact, **options) for exact in (True, False)]
        return JoinResult(*both, box_verdicts(left, right, predicate, method, grid, boxes, tiles, counts=True, **options))
    pairs = materialize(mbr.mbr_join(left, right, boxes, strategy, tiles).select("rid", "sid"))  # the box join runs once
    return finish(verdicts(pairs, left, right, predicate, method, grid, **options), left, right, predicate)


def partitioned_join(left: DataFrame, right: DataFrame, p: int = 2, order: int = 16, tiles: Tiles | None = None, method: str = "onestep_neighbours") -> JoinResult:
    """Dual-run join with a grid of its own for each tile; objects stand in all tiles they meet."""
    tiles = tiles or uniform_tiles(p)
    boxes = materialize(raster_boxes([layer.withColumn("tile_id", F.explode(tiles.touched())) for layer in (left, right)], order))
    a, b = (approximate.build_dual(assign(layer, tiles, boxes), None, method) for layer in (left, right))
    pairs = mbr.mbr_join(left, right, "intersects", "tiled", tiles)
    return finish(filters.dual_filter(pairs, a, b, large=larger_side(left, right)), left, right, "intersects")


def approximate_query(spark: SparkSession, ring: list[tuple[int, int]], grid: GridSpec = GridSpec()) -> DataFrame:
    """Dual runs of one query polygon, built on the driver: a one-row frame to broadcast."""
    pts = np.array(ring, np.int64)
    got = rasterize.onestep(rasterize.Batch(pts, np.array([0, len(pts)]), grid))
    return spark.createDataFrame([(got["cover"][0].tolist(), got["core"][0].tolist())], "cover array<bigint>, core array<bigint>")


def spatial_select(layer: DataFrame, probes: DataFrame, method: str = "dual", grid: GridSpec = GridSpec(), stored: DataFrame | None = None) -> JoinResult:
    """Objects of a layer that meet each query polygon: ``pairs(rid = query, sid = object)``.

    The probes are few (their count is checked) and broadcast; the layer's side stays a narrow pass.
    """
    pairs = mbr.mbr_join(layer, probes, "intersects", "broadcast").select(F.col("sid").alias("rid"), F.col("rid").alias("sid"))
    approx = None
    if stored is not None:
        approx = (approximate_layer(probes, method, "R", grid), stored)
    return finish(verdicts(pairs, probes, layer, "intersects", method, grid, approx=approx), probes, layer, "intersects")


def choose_order(layer: DataFrame, max_runs: int = 2000) -> int:
    """The highest order (at most 16) at which an average object's boundary takes about ``max_runs`` cells."""
    mean = mbr.profile(layer).extent or 1.0
    order = 16
    while order > 1 and 2 * mean / (DOMAIN >> order) > max_runs:
        order -= 1
    return order


def coarsen(dual: DataFrame, to_order: int) -> DataFrame:
    """Dual runs at a lower order: cover lists only, as parents of core cells need not be core."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            order = batch.column("ord").to_numpy()
            for o in np.unique(order).tolist():
                rows = pa.array(np.flatnonzero(order == o))
                got = lists.coarsen(lists.flat(batch.column("cover").take(rows)), o - to_order)
                yield pa.RecordBatch.from_arrays([batch.column("tile_id").take(rows), batch.column("oid").take(rows), pa.array(np.full(len(rows), to_order, np.int32)), lists.to_column(*got)], names=["tile_id", "oid", "ord", "cover"])

    return dual.select("tile_id", "oid", "ord", "cover").mapInArrow(run, "tile_id int, oid long, ord int, cover array<bigint>")
