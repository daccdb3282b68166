"""The box stage: candidate pairs by intersecting or containing bounding boxes."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rasterruns.grid import DOMAIN
from rasterruns.operators.tiles import BOX, Tiles, uniform_tiles

#: Rows up to which a side may be broadcast; beyond, the tiled join takes over.
BROADCAST_ROWS = 100_000
#: Objects a tile should hold on average, and those of one tile beyond which it is dealt over several tasks.
PER_TILE = 64
HOT = 65_536
MOST_TILES = 4096


@dataclass(frozen=True)
class Profile:
    """Objects of a layer, mean width plus height, and mean area of their boxes."""

    objects: int
    extent: float
    area: float


def profile(layer: DataFrame) -> Profile:
    """One aggregate over the boxes, kept with the frame, so that a stored layer is read for it once."""
    if not hasattr(layer, "_profile"):
        w, h = F.col("xmax") - F.col("xmin"), F.col("ymax") - F.col("ymin")
        r = layer.agg(F.count(F.lit(1)), F.avg((w + h).cast("double")), F.avg((w + 1.0) * (h + 1.0))).first()
        layer._profile = Profile(r[0], r[1] or 0.0, r[2] or 1.0)
    return layer._profile


def fitting_tiles(left: DataFrame, right: DataFrame) -> Tiles:
    """As many tiles as keep their contents level whatever the tables hold, but none smaller than a mean object of the larger kind."""
    a, b = profile(left), profile(right)
    wanted = math.isqrt(max(a.objects, b.objects) // PER_TILE) + 1
    largest = DOMAIN / max(1.0, max(a.extent, b.extent) / 2)
    return uniform_tiles(int(max(1, min(wanted, largest, MOST_TILES))))


def _side(df: DataFrame, p: str, tiles: Tiles | None) -> DataFrame:
    columns = [F.col("oid").alias(f"{p}id"), *[F.col(c).alias(f"{p}_{c}") for c in BOX]]
    if tiles is not None:
        columns.append(F.explode(tiles.touched()).alias("tile_id"))
    return df.select(*columns)


def _dealt(r: DataFrame, s: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Both sides with ``part``: the left rows of a hot tile are dealt, the right ones stand in each of its parts."""
    n = r.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HOT)
    hot = F.broadcast(n.select("tile_id", F.ceil(F.col("n") / HOT).cast("int").alias("parts")))  # at most one row for HOT rows of a side
    parts = F.coalesce("parts", F.lit(1))
    left = r.join(hot, "tile_id", "left").withColumn("part", F.pmod(F.xxhash64("rid"), parts).cast("int")).drop("parts")
    right = s.join(hot, "tile_id", "left").withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("parts")
    return left, right


def _meets(predicate: str) -> Column:
    c = F.col
    if predicate == "within":
        return (c("r_xmin") >= c("s_xmin")) & (c("r_xmax") <= c("s_xmax")) & (c("r_ymin") >= c("s_ymin")) & (c("r_ymax") <= c("s_ymax"))
    if predicate == "intersects":
        return (c("r_xmin") <= c("s_xmax")) & (c("s_xmin") <= c("r_xmax")) & (c("r_ymin") <= c("s_ymax")) & (c("s_ymin") <= c("r_ymax"))
    raise ValueError(f"unknown box predicate {predicate}")


def _owned(tiles: Tiles) -> Column:
    """The tile of the common box's lower corner reports the pair; both objects stand there."""
    return F.col("tile_id") == tiles.owner(F.greatest("r_xmin", "s_xmin"), F.greatest("r_ymin", "s_ymin"))


def _sweep(tiles: Tiles, predicate: str):
    """Forward sweep along x within a tile."""

    def run(left, right):
        box = {p: np.stack([t.column(f"{p}_{c}").to_numpy() for c in BOX], 1) if t.num_rows else np.zeros((0, 4), np.int64) for p, t in (("r", left), ("s", right))}
        out_r, out_s = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        order = np.argsort(box["s"][:, 0], kind="stable")
        s = box["s"][order]
        widest = int((s[:, 2] - s[:, 0]).max(initial=0))
        lo = np.searchsorted(s[:, 0], box["r"][:, 0] - widest, "left")
        hi = np.searchsorted(s[:, 0], box["r"][:, 2], "right")
        for i, (a, b) in enumerate(zip(lo.tolist(), hi.tolist(), strict=True)):
            r, t = box["r"][i], s[a:b]
            if predicate == "within":
                ok = (t[:, 0] <= r[0]) & (t[:, 2] >= r[2]) & (t[:, 1] <= r[1]) & (t[:, 3] >= r[3])
            else:
                ok = (t[:, 2] >= r[0]) & (t[:, 1] <= r[3]) & (t[:, 3] >= r[1])
            found = order[a:b][ok]
            out_r.append(np.full(len(found), i))
            out_s.append(found)
        i, j = np.concatenate(out_r), np.concatenate(out_s)
        take = lambda t, c, k: t.column(c).take(pa.array(k)) if t.num_rows else pa.array([], pa.int32() if c == "tile_id" else pa.int64())
        tile = take(left, "tile_id", i)
        names = ["tile_id", "rid", "sid", *(f"{p}_{c}" for p in "rs" for c in BOX)]
        cols = [tile, take(left, "rid", i), take(right, "sid", j), *(take(t, f"{p}_{c}", k) for p, t, k in (("r", left, i), ("s", right, j)) for c in BOX)]
        return pa.table(dict(zip(names, cols, strict=True)))

    return run


def mbr_join(left: DataFrame, right: DataFrame, predicate: str = "intersects", strategy: str = "tiled", tiles: Tiles | None = None) -> DataFrame:
    """Candidate pairs ``(tile_id, rid, sid)``; every pair once, without a distinct.

    ``tiled`` (default): an equi-join on tiles with range predicates and an
    owner test; left objects of a tile with more than HOT are dealt over parts,
    each with a copy of the tile's right objects; ``sweep``: the same with a
    sorted sweep in each part;
    ``broadcast``: the right side is sent whole if its checked count allows,
    else ``tiled``; ``nested``: all pairs, the baseline.
    """
    if strategy == "broadcast" and right.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
        strategy = "tiled"
    if strategy in ("broadcast", "nested"):
        r, s = _side(left, "r", None), _side(right, "s", None)
        pairs = r.join(F.broadcast(s) if strategy == "broadcast" else s, _meets(predicate))
        return pairs.select(F.lit(0).alias("tile_id"), "rid", "sid")
    tiles = tiles or fitting_tiles(left, right)
    r, s = _dealt(_side(left, "r", tiles), _side(right, "s", tiles))
    if strategy == "tiled":
        pairs = r.join(s, ["tile_id", "part"]).where(_meets(predicate))
    elif strategy == "sweep":
        fields = ", ".join(f"{p}_{c} long" for p in "rs" for c in BOX)
        pairs = r.groupBy("tile_id", "part").cogroup(s.groupBy("tile_id", "part")).applyInArrow(_sweep(tiles, predicate), f"tile_id int, rid long, sid long, {fields}")
    else:
        raise ValueError(f"unknown strategy {strategy}")
    return pairs.where(_owned(tiles)).select("tile_id", "rid", "sid")


def window(layer: DataFrame, box: tuple[int, int, int, int]) -> DataFrame:
    """Objects whose box meets a window; plain range predicates, so Parquet statistics prune."""
    return layer.where((F.col("xmin") <= box[2]) & (F.col("xmax") >= box[0]) & (F.col("ymin") <= box[3]) & (F.col("ymax") >= box[1]))
