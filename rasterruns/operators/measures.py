"""Effectiveness, space and cost measures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.grid import GridSpec
from rasterruns.operators import approximate


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def layer_stats(layers: dict[str, DataFrame]) -> DataFrame:
    """Objects, vertices and box areas of layers (averages are the ratios)."""
    area = (F.col("xmax") - F.col("xmin")) * (F.col("ymax") - F.col("ymin"))
    return _all([x.agg(F.lit(n).alias("layer"), F.count(F.lit(1)).alias("objects"), F.sum("n_vertices").alias("vertices"), F.sum(area).alias("box_area")) for n, x in layers.items()])


def _length(lists: str):
    even = F.filter(F.sequence(F.lit(0), F.size(lists)), lambda i: (i % 2 == 0) & (i < F.size(lists)))
    return F.aggregate(even, F.lit(0).cast("long"), lambda a, i: a + F.get(lists, i + 1) - F.get(lists, i))


def run_stats(dual: DataFrame) -> DataFrame:
    """Runs and cells of each object's lists."""
    runs = lambda c: (F.size(c) / 2).cast("long")
    return dual.select("oid", runs("cover").alias("cover_runs"), runs("core").alias("core_runs"), _length("cover").alias("cover_cells"), _length("core").alias("core_cells"))


def pip_counts(layer: DataFrame, grid: GridSpec) -> DataFrame:
    """Centre tests by construction: every gap, gaps without a labelled neighbour, flooded regions."""
    got = [approximate.build_dual(layer, grid, m).agg(F.lit(m).alias("method"), F.sum("n_gaps").alias("gaps"), F.sum("n_pip").alias("tests")) for m in ("onestep_pip", "onestep_neighbours", "flood")]
    return _all(got)


def space_report(layers: dict[str, DataFrame], grid: GridSpec, max_cells: int = 750) -> DataFrame:
    """Bytes of each representation by layer: 4 a list end, coded runs with their bytes, 2 bits a raster cell."""
    out = []
    for name, x in layers.items():

        def row(kind: str, frame: DataFrame, size) -> None:
            out.append(frame.agg(F.lit(name).alias("layer"), F.lit(kind).alias("kind"), F.sum(size).cast("long").alias("bytes")))

        row("geometry", x, F.col("n_vertices") * 16)
        row("box", x, F.lit(36))
        row("dual", approximate.build_dual(x, grid), 4 * (F.size("cover") + F.size("core")))
        row("dual_compressed", approximate.build_dual(x, grid, compressed=True), F.length("cover") + F.length("core"))
        row("coded", approximate.build_coded(x, grid), 4 * F.size("runs") + F.length("code"))
        row("local_raster", approximate.build_local_raster(x, max_cells), 16 + F.ceil(F.size("cells") / 4))
        row("corner_hull", approximate.build_corner_hull(x), 8 * (F.size("corners") + F.size("hull")))
    return _all(out)


def ratio_report(space: DataFrame, old: str = "coded", new: tuple[str, ...] = ("dual", "dual_compressed")) -> DataFrame:
    """How many times smaller the new lists are, in basis points: least, greatest and mean ratio over layers."""
    a = space.where(F.col("kind") == old).select("layer", F.col("bytes").alias("old"))
    b = space.where(F.col("kind").isin(*new)).select("layer", "kind", F.col("bytes").alias("new"))
    bp = a.join(b, "layer").select("kind", F.expr("old * 10000 div new").alias("bp"))
    return bp.groupBy("kind").agg(F.min("bp").alias("least"), F.max("bp").alias("most"), F.expr("sum(bp) div count(1)").alias("mean"))


def line_bytes(lines: DataFrame, grid: GridSpec) -> DataFrame:
    """Bytes of a path as cells (4 each) and as runs (8 each)."""
    a = approximate.build_line_cells(lines, grid).select("oid", (4 * F.size("cells")).cast("long").alias("as_cells"))
    b = approximate.build_line_cells(lines, grid, as_runs=True).select("oid", (4 * F.size("cells")).cast("long").alias("as_runs"))
    return a.join(b, "oid")


def upscaled_types(raster: DataFrame, levels: int) -> DataFrame:
    """Local raster cells at a coarser level, by the rule the filter uses, as a grouped aggregate."""
    n = 1 << (2 * levels)
    c = raster.select("oid", F.explode("cells").alias("c")).select("oid", F.shiftright("c.cx", levels).alias("cx"), F.shiftright("c.cy", levels).alias("cy"), F.col("c.type").alias("t"))
    g = c.groupBy("oid", "cx", "cy").agg(F.count_if(F.col("t") == 3).alias("full"), F.count_if(F.col("t") == 2).alias("strong"))
    score = 2 * F.col("full") + F.col("strong")
    kind = F.when(F.col("full") == n, 3).when((score > n) | ((score == n) & (F.col("strong") > 0)), 2).otherwise(1)
    return g.select("oid", "cx", "cy", kind.cast("long").alias("type"))
