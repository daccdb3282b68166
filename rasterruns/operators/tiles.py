"""Space partitions: tiles as unions of base cells, per-tile grids, owners of pairs."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rasterruns.grid import DOMAIN

BOX = ("xmin", "ymin", "xmax", "ymax")


@dataclass(frozen=True)
class Tiles:
    """``p`` x ``p`` half-open base cells; ``leaf`` names the tile of each, or every cell is its own tile."""

    p: int
    leaf: tuple[int, ...] | None = None

    def base(self, v: Column) -> Column:
        return F.least(F.greatest(F.floor(v * self.p / DOMAIN), F.lit(0)), F.lit(self.p - 1)).cast("int")

    def _tile(self, i: Column) -> Column:
        return i if self.leaf is None else F.get(F.array(*[F.lit(x) for x in self.leaf]), i)

    def owner(self, x: Column, y: Column) -> Column:
        """The tile that holds a point."""
        return self._tile(self.base(x) * self.p + self.base(y))

    def touched(self) -> Column:
        """All tiles that a row's box meets."""
        cols = F.sequence(self.base(F.col("xmin")), self.base(F.col("xmax")))
        rows = F.sequence(self.base(F.col("ymin")), self.base(F.col("ymax")))
        cells = F.flatten(F.transform(cols, lambda a: F.transform(rows, lambda b: a * self.p + b)))
        if self.leaf is None:
            return cells
        table = F.array(*[F.lit(x) for x in self.leaf])
        return F.array_distinct(F.transform(cells, lambda c: F.get(table, c)))

    def count(self) -> int:
        return self.p * self.p if self.leaf is None else len(set(self.leaf))


def uniform_tiles(p: int) -> Tiles:
    return Tiles(p)


def quadtree_tiles(layers: list[DataFrame], max_per_tile: int, levels: int = 5) -> Tiles:
    """Uneven tiles, smaller where objects are denser.

    One aggregate counts box centres by base cell; the 4^levels counts are a
    fixed number, so the split itself runs on the driver.
    """
    p = 1 << levels
    t = Tiles(p)
    counts = [0] * (p * p)
    for layer in layers:
        cell = t.owner(F.floor((F.col("xmin") + F.col("xmax")) / 2), F.floor((F.col("ymin") + F.col("ymax")) / 2))
        for c, n in layer.groupBy(cell.alias("c")).count().collect():
            counts[c] += n
    leaf, tiles = [0] * (p * p), 0

    def split(x: int, y: int, side: int) -> None:
        nonlocal tiles
        cells = [(x + i) * p + y + j for i in range(side) for j in range(side)]
        if side == 1 or sum(counts[c] for c in cells) <= max_per_tile:
            for c in cells:
                leaf[c] = tiles
            tiles += 1
            return
        h = side // 2
        for a, b in ((0, 0), (h, 0), (0, h), (h, h)):
            split(x + a, y + b, h)

    split(0, 0, p)
    return Tiles(p, tuple(leaf))


def replicate(layer: DataFrame, tiles: Tiles) -> DataFrame:
    """One row for each tile that an object's box meets."""
    return layer.withColumn("tile_id", F.explode(tiles.touched()))


def raster_boxes(layers: list[DataFrame], order: int) -> DataFrame:
    """Per tile the grid over the contents of all layers, padded by a cell: g_order, g_x0, g_y0, g_cell.

    One row a tile; bounded by the partition, not by the data.
    """
    if order > 16:
        raise ValueError("tiles take orders up to 16: ids must stay within 32 bits")
    all_ = None
    for layer in layers:
        part = layer.select("tile_id", *BOX)
        all_ = part if all_ is None else all_.union(part)
    box = all_.groupBy("tile_id").agg(F.min("xmin").alias("x0"), F.min("ymin").alias("y0"), F.greatest(F.max("xmax") - F.min("xmin"), F.max("ymax") - F.min("ymin")).alias("extent"))
    cell = F.ceil((F.col("extent") + 1) / ((1 << order) - 2)).cast("int") if order > 1 else (F.col("extent") + 1).cast("int")
    return box.select("tile_id", F.lit(order).alias("g_order"), (F.col("x0") - cell).cast("int").alias("g_x0"), (F.col("y0") - cell).cast("int").alias("g_y0"), cell.alias("g_cell"))


def assign(layer: DataFrame, tiles: Tiles, boxes: DataFrame) -> DataFrame:
    """Replicated objects with their tile's grid."""
    return replicate(layer, tiles).join(F.broadcast(boxes), "tile_id")


def replication(layer: DataFrame, tiles: Tiles) -> DataFrame:
    """Objects, replicas, and tiles in use."""
    return replicate(layer, tiles).agg(F.count_distinct("oid").alias("objects"), F.count(F.lit(1)).alias("replicas"), F.count_distinct("tile_id").alias("tiles"))
