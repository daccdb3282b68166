"""Streams: track segments from events, segments against stored polygons, and windowed counts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rasterruns.grid import DOMAIN, GridSpec
from rasterruns.operators import approximate, filters, mbr
from rasterruns.operators.refine import refine
from rasterruns.operators.tiles import Tiles, uniform_tiles
from rasterruns.runtime import materialize, release
from rasterruns.sources.layers import STEPS, with_mbr

SEGMENT = "oid long, user_id long, ts timestamp, x0 long, y0 long, x1 long, y1 long"


def place(e: DataFrame) -> DataFrame:
    """Events with a position of their own, from id and value (a stand-in for reported positions)."""
    spread = lambda salt: F.pmod(F.xxhash64("user_id", F.lit(salt)), F.lit(DOMAIN // 2)) + DOMAIN // 4
    step = lambda i: F.coalesce(*[F.when(F.col("event_type") == t, F.lit(v[i])) for t, v in STEPS.items()], F.lit(0))
    far = (40 + F.floor(F.col("value") * 8)).cast("long")
    return e.select("event_id", "user_id", "ts", (spread(1) + step(0) * far).alias("x"), (spread(2) + step(1) * far).alias("y"))


def segments(events: DataFrame) -> DataFrame:
    """Batch form: a segment from each event to the user's event before it."""
    line = Window.partitionBy("user_id").orderBy("ts", "event_id")
    p = place(events)
    p = p.select("event_id", "user_id", "ts", F.lag("x").over(line).alias("x0"), F.lag("y").over(line).alias("y0"), F.col("x").alias("x1"), F.col("y").alias("y1"))
    return p.where("x0 IS NOT NULL").select(F.col("event_id").alias("oid"), "user_id", "ts", "x0", "y0", "x1", "y1")


def _extend(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Keep each user's last position; emit a segment for every event after the first."""
    last = state.get if state.exists else None
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    out = []
    for r in rows.itertuples():
        if last is not None:
            out.append((r.event_id, key[0], r.ts, last[0], last[1], r.x, r.y))
        last = (r.x, r.y)
    state.update(last)
    yield pd.DataFrame(out, columns=["oid", "user_id", "ts", "x0", "y0", "x1", "y1"])


def stream_segments(events: DataFrame) -> DataFrame:
    """Stateful form on a stream: one last position a user is all the state.

    Segments follow the order of arrival: events are sorted within a
    micro-batch, and one that arrives in a later batch than its successors is
    joined to the last position seen, unlike in the batch form.
    """
    return place(events).groupBy("user_id").applyInPandasWithState(_extend, SEGMENT, "x long, y long", "append", GroupStateTimeout.NoTimeout)


def as_paths(segs: DataFrame) -> DataFrame:
    ends = [F.struct(F.col(f"x{i}").alias("x"), F.col(f"y{i}").alias("y")) for i in (0, 1)]
    return with_mbr(segs.select("oid", F.array(*ends).alias("path")), "path")


def filter_segments(segs: DataFrame, polygons: DataFrame, grid: GridSpec, stored: DataFrame | None = None, tiles: Tiles | None = None) -> DataFrame:
    """Segments against stored polygons' dual runs: ``(rid, sid, verdict)`` without misses (a batch)."""
    paths = as_paths(segs)
    runs = stored if stored is not None else approximate.build_dual(polygons, grid)
    pairs = mbr.mbr_join(polygons, paths, tiles=tiles or uniform_tiles(32)).drop("tile_id")
    got = filters.dual_line_filter(pairs, runs, approximate.build_line_cells(paths, grid))
    return got.where("verdict <> 'miss'").select("rid", "sid", "verdict")


def select_stream(segs: DataFrame, polygons: DataFrame, grid: GridSpec, sink: str, checkpoint: str, stored: DataFrame | None = None, exact: bool = True) -> DataStreamWriter:
    """Stream-static selection: each micro-batch of segments against the stored polygons, appended as Parquet.

    ``exact`` adds the exact test: hits and confirmed pairs ``(rid, sid)``; else
    verdicts.  A batch writes its own folder ``batch=N``, which a repeated
    batch replaces, so results hold every batch once.  The polygons' lists are
    built once, before the stream starts.
    """
    runs = stored if stored is not None else materialize(approximate.build_dual(polygons, grid))

    def batch(rows: DataFrame, number: int) -> None:
        mine = materialize(rows)
        found = materialize(filter_segments(mine, polygons, grid, runs))
        out = found
        if exact:
            unsure = refine(found.where("verdict = 'unsure'"), polygons, as_paths(mine), "line")
            out = found.where("verdict = 'hit'").select("rid", "sid").unionByName(unsure)
        out.write.mode("overwrite").parquet(f"{sink}/batch={number}")
        release(mine, found)

    return segs.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)


def _timed(stream: DataFrame, at: str, late: str) -> DataFrame:
    """The stream with its event time as a point in time, under a watermark."""
    return stream.withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, late)


def windowed_counts(stream: DataFrame, at: str, keys: list[str], width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts by window and keys; rows later than ``late`` are dropped by the watermark."""
    w = F.window(at, width, slide) if slide else F.window(at, width)
    return _timed(stream, at, late).groupBy(w, *keys).agg(F.count(F.lit(1)).alias("n"))


def session_counts(stream: DataFrame, at: str, keys: list[str], gap: str, late: str = "1 hour") -> DataFrame:
    return _timed(stream, at, late).groupBy(*keys, F.session_window(at, gap)).agg(F.count(F.lit(1)).alias("n"))


def deduplicated(stream: DataFrame, at: str, keys: list[str], late: str = "1 hour") -> DataFrame:
    """The first of equal events within the watermark."""
    return _timed(stream, at, late).dropDuplicatesWithinWatermark(keys)


def follow_ups(stream: DataFrame, first: str, then: str, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: events of one type with those of another that follow within an interval."""
    a = stream.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("first_id"), F.col("ts").cast("timestamp").alias("first_ts")).withWatermark("first_ts", late)
    b = stream.where(F.col("event_type") == then).select(F.col("user_id").alias("then_user"), F.col("event_id").alias("then_id"), F.col("ts").cast("timestamp").alias("then_ts")).withWatermark("then_ts", late)
    near = F.expr(f"user_id = then_user AND then_ts >= first_ts AND then_ts <= first_ts + INTERVAL {within}")
    return a.join(b, near)
