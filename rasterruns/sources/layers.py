"""Polygon and linestring layers derived from the test tables by exact integer arithmetic.

One recipe is rendered for Spark (Column expressions, vertices in an Arrow stage)
and for DuckDB (SQL text for the oracles), so both see the same coordinates.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rasterruns.grid import DOMAIN

_M = (1 << 31) - 1
_LAYER_STEP = 1_000_003


@dataclass(frozen=True)
class Recipe:
    table: str
    key: str
    layer_id: int
    n: int
    rmin: int
    rmax: int


#: The layers' tables, keys, ids, vertex counts and radii.
RECIPES = {
    "ponds": Recipe("orders", "o_orderkey", 1, 12, 40, 600),
    "sites": Recipe("customer", "c_custkey", 2, 20, 400, 4000),
    "zones": Recipe("part", "p_partkey", 3, 64, 2000, 9000),
    "counties": Recipe("supplier", "s_suppkey", 4, 256, 8000, 40000),
    "provinces": Recipe("nation", "n_nationkey", 5, 1024, 60000, 120000),
    "lakes": Recipe("part", "p_partkey", 7, 24, 200, 3000),
    "parks": Recipe("customer", "c_custkey", 8, 32, 200, 4000),
}
#: The direction of a track step by event type.
STEPS = {"click": (1, 0), "view": (0, 1), "purchase": (-1, 0), "error": (0, -1), "signup": (1, 1)}
PROBES = 1000


def directions(n: int) -> tuple[list[int], list[int]]:
    at = [2 * math.pi * (i + 0.5) / n for i in range(n)]
    return [round(65536 * math.cos(a)) for a in at], [round(65536 * math.sin(a)) for a in at]


def _mix(z: Column) -> Column:
    return (z.bitwiseXOR(F.shiftright(z, 15)) * F.lit(2246822519).cast("long")).bitwiseAND(F.lit(_M).cast("long"))


def _h(k: Column, salt: int) -> Column:
    return _mix(_mix((k * 2654435 + (salt * 97531 + 12345)).bitwiseAND(F.lit(_M).cast("long"))))


def _keyed(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``(oid, grp)`` of each object."""
    q = RECIPES[name]
    rows = spark.read.parquet(f"{sf_dir}/{q.table}.parquet")
    if name == "parks":
        nation = spark.read.parquet(f"{sf_dir}/nation.parquet").select("n_nationkey", "n_regionkey")
        rows = rows.join(nation, rows["c_nationkey"] == nation["n_nationkey"])
        grp = F.col("n_regionkey").cast("long")
    elif name == "lakes":
        grp = F.col(q.key) % 5
    else:
        grp = F.lit(None).cast("long")
    return rows.select(F.col(q.key).cast("long").alias("oid"), grp.cast("long").alias("grp"))


def _hashed(k: np.ndarray, salt: int) -> np.ndarray:
    """``_h`` of whole arrays."""
    z = (k * 2654435 + (salt * 97531 + 12345)) & _M
    for _ in range(2):
        z = ((z ^ (z >> 15)) * 2246822519) & _M
    return z


def _centres(name: str, kk: np.ndarray, grp: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Centres and radii: as Column expressions, where each hash repeats its argument four times, they took 13 us a row."""
    q, h = RECIPES[name], _hashed
    m = q.rmax + 64
    r = q.rmin + h(kk, 4) % (q.rmax - q.rmin)
    if grp is not None:
        return 200 + m + grp * 209715 + h(kk, 3) % (209315 - 2 * m), 400000 + m + h(kk, 8) % (209315 - 2 * m), r
    spread, cl = h(kk, 7) % 2 == 0, h(kk, 2) % 25

    def axis(own: int, cluster: int) -> np.ndarray:
        near = 131072 - 32768 + h(cl, cluster) % 786432 + h(kk, own) % 65536
        return np.where(spread, m + h(kk, own) % (DOMAIN - 2 * m), np.minimum(np.maximum(near, m), DOMAIN - m - 1))

    return axis(3, 6), axis(8, 9), r


def _axis(name: str):
    return lambda p: p[name]


def with_mbr(df: DataFrame, points: str = "ring") -> DataFrame:
    """Add the bounding box as four columns, so that Parquet statistics and range predicates apply."""
    for f, n in ((F.array_min, "min"), (F.array_max, "max")):
        for a in ("x", "y"):
            df = df.withColumn(f"{a}{n}", f(F.transform(points, _axis(a))))
    return df.withColumn("n_vertices", F.size(points))


_BOX = ("xmin", "ymin", "xmax", "ymax")


def _ring(df: DataFrame, points: Column, *keep: str) -> DataFrame:
    return with_mbr(df.select(*keep, points.alias("ring"))).select(*keep, "ring", *_BOX, "n_vertices")


def load_layer(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Layer by name: oid, grp, ring (or path), box, n_vertices."""
    if name == "tracks":
        return load_tracks(spark, sf_dir)
    if name == "probes":
        picked = load_layer(spark, sf_dir, "counties")
        k = F.col("oid") + RECIPES["counties"].layer_id * _LAYER_STEP
        return picked.orderBy(_h(k, 11), "oid").limit(PROBES)  # the query set is a top-k by hash
    if name == "blobs":
        return load_blobs(spark, sf_dir)
    columns = "oid long, grp long, ring array<struct<x:bigint,y:bigint>>, xmin long, ymin long, xmax long, ymax long, n_vertices int"
    return _keyed(spark, sf_dir, name).mapInArrow(_rings(name), columns)


def _rings(name: str):
    """Rings with their boxes from keys, a batch at once: lambdas over arrays took 12 us a vertex."""
    q = RECIPES[name]
    n, h = q.n, _hashed
    dx, dy = (np.array(v, np.int64) for v in directions(n))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, max(1, 1_000_000 // n)):
                rows = batch.slice(at, max(1, 1_000_000 // n))
                kk = rows.column("oid").to_numpy().astype(np.int64)[:, None] + q.layer_id * _LAYER_STEP
                cx, cy, r = _centres(name, kk, rows.column("grp").to_numpy().astype(np.int64)[:, None] if name in ("lakes", "parks") else None)
                radius = r * (600 + h(kk * 1031 + np.arange(n), 5) % 401) // 1000
                x, y = cx + (dx * radius >> 16), cy + (dy * radius >> 16)
                points = pa.StructArray.from_arrays([pa.array(x.ravel()), pa.array(y.ravel())], names=["x", "y"])
                ring = pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * n), points)
                box = [pa.array(v) for v in (x.min(1), y.min(1), x.max(1), y.max(1))]
                yield pa.RecordBatch.from_arrays([rows.column("oid"), rows.column("grp"), ring, *box, pa.array(np.full(len(rows), n, np.int32))], names=["oid", "grp", "ring", *_BOX, "n_vertices"])

    return run


def load_blobs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spiky stars: 64 radii from each embedding's components, centres spread like the other layers'.

    Vectors of another length or with a component that is null, not finite or
    beyond 1 make no shape (a star must stay inside the domain).
    """
    whole = F.forall("embedding", lambda e: F.coalesce(F.abs(e.cast("double")) <= 1, F.lit(False)))  # NaN counts as greater
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").where((F.size("embedding") == 64) & whole)
    dx, dy = (F.array(*[F.lit(v).cast("long") for v in d]) for d in directions(64))
    kk = F.col("vec_id") + 10 * _LAYER_STEP
    m = 5000
    t = rows.select(F.col("vec_id").alias("oid"), F.lit(None).cast("long").alias("grp"), "embedding", (m + _h(kk, 3) % (DOMAIN - 2 * m)).alias("cx"), (m + _h(kk, 8) % (DOMAIN - 2 * m)).alias("cy"), dx.alias("dx"), dy.alias("dy"))

    def vertex(e: Column, i: Column) -> Column:
        r = F.lit(300) + F.floor(F.abs(e.cast("double")) * 4096)
        return F.struct((F.col("cx") + F.shiftright(F.get("dx", i) * r, 16)).alias("x"), (F.col("cy") + F.shiftright(F.get("dy", i) * r, 16)).alias("y"))

    return _ring(t, F.transform("embedding", vertex), "oid", "grp")


def load_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Linestrings of up to 20 points: each user's events as steps of a walk, cut into chunks."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    line = Window.partitionBy("user_id").orderBy("ts", "event_id")
    step = {a: F.coalesce(*[F.when(F.col("event_type") == t, F.lit(v[i])) for t, v in STEPS.items()], F.lit(0)) for i, a in enumerate("xy")}
    length = (40 + F.floor(F.col("value") * 8)).cast("long")
    e = e.select("user_id", "ts", "event_id", F.row_number().over(line).alias("rn"), *[F.sum(step[a] * length).over(line.rowsBetween(Window.unboundedPreceding, 0)).alias(f"s{a}") for a in "xy"])
    k = F.col("user_id") + 9 * _LAYER_STEP
    at = [F.least(F.greatest(262144 + _h(k, salt) % 524288 + F.col(f"s{a}"), F.lit(64)), F.lit(DOMAIN - 65)).alias(a) for a, salt in (("x", 3), ("y", 8))]
    points = e.select((F.col("user_id") * 1000 + F.floor((F.col("rn") - 1) / 20)).alias("oid"), "rn", *at)
    paths = points.groupBy("oid").agg(F.array_sort(F.collect_list(F.struct("rn", "x", "y"))).alias("p")).where(F.size("p") > 1)
    paths = paths.select("oid", F.lit(None).cast("long").alias("grp"), F.transform("p", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y"))).alias("path"))
    return with_mbr(paths, "path").select("oid", "grp", "path", *_BOX, "n_vertices")


# ---- the same recipe as DuckDB SQL ----


def _dmix(z: str) -> str:
    return f"((xor({z}, ({z}) >> 15) * 2246822519) & {_M})"


def _dh(k: str, salt: int) -> str:
    return _dmix(_dmix(f"((({k}) * 2654435 + {salt * 97531 + 12345}) & {_M})"))


def duckdb_layer(name: str, only: int | None = None) -> str:
    """CTEs ``{name}_v(oid, grp, i, x, y)`` (vertices) and ``{name}(oid, grp, xmin, ymin, xmax, ymax, n)``.

    ``only``: the objects of one group.
    """
    if name == "tracks":
        return _duckdb_tracks()
    if name == "probes":
        q = RECIPES["counties"]
        key = _dh(f"oid + {q.layer_id * _LAYER_STEP}", 11)
        return f"{duckdb_layer('counties')}, probes AS (SELECT * FROM counties ORDER BY {key}, oid LIMIT {PROBES}), probes_v AS (SELECT v.* FROM counties_v v JOIN probes USING (oid))"
    q = RECIPES[name]
    key = f"CAST({q.key} AS BIGINT)"
    kk = f"({key} + {q.layer_id * _LAYER_STEP})"
    m = q.rmax + 64
    source, grp = q.table, "NULL::BIGINT"
    if name == "parks":
        source, grp = "customer JOIN nation ON c_nationkey = n_nationkey", "CAST(n_regionkey AS BIGINT)"
    elif name == "lakes":
        grp = f"{key} % 5"
    if name in ("lakes", "parks"):
        x = f"{200 + m} + ({grp}) * 209715 + {_dh(kk, 3)} % {209315 - 2 * m}"
        y = f"{400000 + m} + {_dh(kk, 8)} % {209315 - 2 * m}"
    else:
        cl = f"({_dh(kk, 2)} % 25)"

        def axis(own: int, cluster: int) -> str:
            near = f"{131072 - 32768} + {_dh(cl, cluster)} % 786432 + {_dh(kk, own)} % 65536"
            return f"CASE WHEN {_dh(kk, 7)} % 2 = 0 THEN {m} + {_dh(kk, own)} % {DOMAIN - 2 * m} ELSE least(greatest({near}, {m}), {DOMAIN - m - 1}) END"

        x, y = axis(3, 6), axis(8, 9)
    dx, dy = directions(q.n)
    r = f"((r * (600 + {_dh('kk * 1031 + i', 5)} % 401)) // 1000)"
    return f"""{name}_c AS (SELECT {key} AS oid, {grp} AS grp, {kk} AS kk, {x} AS cx, {y} AS cy, {q.rmin} + {_dh(kk, 4)} % {q.rmax - q.rmin} AS r FROM {source}),
{name}_r AS (SELECT oid, grp, i, cx, cy, {r} AS ri FROM {name}_c, (SELECT unnest(range({q.n})) AS i)),
{name}_v AS (SELECT oid, grp, i, cx + (({dx}[i + 1] * ri) >> 16) AS x, cy + (({dy}[i + 1] * ri) >> 16) AS y FROM {name}_r),
{name} AS (SELECT oid, any_value(grp) AS grp, min(x) AS xmin, min(y) AS ymin, max(x) AS xmax, max(y) AS ymax, count(*) AS n FROM {name}_v{'' if only is None else f' WHERE grp = {only}'} GROUP BY oid)"""


def _duckdb_tracks() -> str:
    step = {a: "CASE event_type " + " ".join(f"WHEN '{t}' THEN {v[i]}" for t, v in STEPS.items()) + " ELSE 0 END" for i, a in enumerate("xy")}
    length = "(40 + CAST(floor(value * 8) AS BIGINT))"
    k = f"(user_id + {9 * _LAYER_STEP})"
    at = ", ".join(f"least(greatest(262144 + {_dh(k, salt)} % 524288 + sum({step[a]} * {length}) OVER w, 64), {DOMAIN - 65})::BIGINT AS {a}" for a, salt in (("x", 3), ("y", 8)))
    return f"""tracks_p AS (SELECT user_id, row_number() OVER w AS rn, {at} FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)),
tracks_a AS (SELECT user_id * 1000 + (rn - 1) // 20 AS oid, (rn - 1) % 20 AS i, x, y FROM tracks_p),
tracks AS (SELECT oid, min(x) AS xmin, min(y) AS ymin, max(x) AS xmax, max(y) AS ymax, count(*) AS n FROM tracks_a GROUP BY oid HAVING count(*) > 1),
tracks_v AS (SELECT a.* FROM tracks_a a JOIN tracks USING (oid))"""
