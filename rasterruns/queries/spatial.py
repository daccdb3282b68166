"""Queries of the spatial methods, variants, baselines and measures, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rasterruns.functions import codec, hilbert
from rasterruns.grid import DOMAIN, DOMAIN_BITS, GridSpec
from rasterruns.operators import approximate, cells, filters, mbr, measures, tiles
from rasterruns.operators.refine import refine
from rasterruns.plans import join
from rasterruns.queries import oracle
from rasterruns.runtime import materialize, shared_file
from rasterruns.sources import store, wkt
from rasterruns.sources.layers import duckdb_layer, load_layer

#: Orders at which the oracles enumerate cells.
FINE, COARSE = 11, 8
_layers: dict = {}


def layer(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A layer, written once a session: the stored collection that queries start from."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _layers:
        _layers[key] = materialize(load_layer(spark, sf_dir, name))
    return _layers[key]


def exploded(dual: DataFrame) -> DataFrame:
    """Run lists as rows (oid, list, st, en)."""
    out = None
    for name in ("cover", "core"):
        even = F.filter(F.sequence(F.lit(0), F.size("v")), lambda i: (i % 2 == 0) & (i < F.size("v")))
        part = dual.select("oid", F.lit(name).alias("list"), F.col(name).alias("v"))
        part = part.withColumn("r", F.explode(F.transform(even, lambda i: F.struct(F.get("v", i).alias("st"), F.get("v", i + 1).alias("en")))))
        part = part.select("oid", "list", "r.st", "r.en")
        out = part if out is None else out.unionByName(part)
    return out


def _runs_sql(name: str, order: int) -> str:
    h = hilbert.duckdb_hilbert("cx", "cy", order)
    return f"""WITH {duckdb_layer(name)}, {oracle.cells(name, order)},
ids AS (SELECT oid, 'cover' AS list, {h} AS h FROM {name}_cells UNION ALL SELECT oid, 'core', {h} FROM {name}_core),
marked AS (SELECT *, h - row_number() OVER (PARTITION BY oid, list ORDER BY h) AS g FROM ids)
SELECT oid, list, min(h) AS st, max(h) + 1 AS en FROM marked GROUP BY oid, list, g"""


def _counts(result: join.JoinResult) -> DataFrame:
    return result.verdicts.groupBy("verdict").agg(F.count(F.lit(1)).alias("n"))


def _pairs(result: join.JoinResult) -> DataFrame:
    return result.pairs.select("rid", "sid")


Q: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---- curve, grid, cells ----


@query("grid_cell_counts", f"WITH {duckdb_layer('ponds')} SELECT xmin >> 12 AS cx, ymin >> 12 AS cy, count(*) AS n FROM ponds GROUP BY ALL")
def _(spark, d):
    x, y = GridSpec(8).cell_of(F.col("xmin"), F.col("ymin"))
    return layer(spark, d, "ponds").groupBy(x.alias("cx"), y.alias("cy")).agg(F.count(F.lit(1)).alias("n"))


@query("hilbert_encode", f"WITH {duckdb_layer('ponds')} SELECT oid, {hilbert.duckdb_hilbert('(xmin >> 4)', '(ymin >> 4)', 16)} AS hid FROM ponds")
def _(spark, d):
    return layer(spark, d, "ponds").select("oid", hilbert.hilbert_id(F.shiftright("xmin", 4), F.shiftright("ymin", 4), 16).alias("hid"))


@query("hilbert_roundtrip", f"WITH {duckdb_layer('ponds')} SELECT oid, xmin >> 4 AS cx, ymin >> 4 AS cy FROM ponds")
def _(spark, d):
    c = hilbert.hilbert_cell(hilbert.hilbert_id(F.shiftright("xmin", 4), F.shiftright("ymin", 4), 16), 16)
    return layer(spark, d, "ponds").select("oid", c.alias("c")).select("oid", "c.cx", "c.cy")


@query("hilbert_prefix", f"WITH {duckdb_layer('ponds')} SELECT oid, {hilbert.duckdb_hilbert('(xmin >> 10)', '(ymin >> 10)', 10)} AS hid FROM ponds")
def _(spark, d):
    fine = hilbert.hilbert_id(F.shiftright("xmin", 4), F.shiftright("ymin", 4), 16)
    return layer(spark, d, "ponds").select("oid", hilbert.coarsen_id(fine, 16, 10).alias("hid"))


@query("cells_to_runs", f"""WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)}, ids AS (SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS h FROM sites_edge),
m AS (SELECT *, h - row_number() OVER (PARTITION BY oid ORDER BY h) AS g FROM ids) SELECT oid, min(h) AS st, max(h) + 1 AS en FROM m GROUP BY oid, g""")
def _(spark, d):
    return cells.to_runs(cells.edge_cells(layer(spark, d, "sites"), GridSpec(FINE)))


@query("runs_to_cells", f"WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)} SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS hid FROM sites_edge")
def _(spark, d):
    return cells.explode_runs(cells.to_runs(cells.edge_cells(layer(spark, d, "sites"), GridSpec(FINE))))


# ---- constructions ----


@query("edge_cells", f"WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)} SELECT oid, cx, cy FROM sites_edge")
def _(spark, d):
    return cells.edge_cells(layer(spark, d, "sites"), GridSpec(FINE)).select("oid", "cx", "cy")


@query("core_scanline", f"WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)} SELECT oid, cx, cy FROM sites_core")
def _(spark, d):
    return cells.scanline_core(layer(spark, d, "sites"), GridSpec(FINE)).select("oid", "cx", "cy")


def _core_of(method: str, name: str, order: int):
    def run(spark, d):
        dual = approximate.build_dual(layer(spark, d, name), GridSpec(order), method)
        runs = exploded(dual).where("list = 'core'").select("oid", F.explode(F.sequence("st", F.col("en") - 1)).alias("hid"))
        c = hilbert.hilbert_cell(F.col("hid"), order)
        return runs.select("oid", c.alias("c")).select("oid", "c.cx", "c.cy")

    return run


query("core_flood", f"WITH {duckdb_layer('counties')}, {oracle.cells('counties', COARSE)} SELECT oid, cx, cy FROM counties_core")(_core_of("flood", "counties", COARSE))

for _name, _method, _layer, _order in (
    ("dual_runs_scanline", "scanline", "sites", FINE),
    ("dual_runs_flood", "flood", "sites", FINE),
    ("dual_runs_clip", "clip", "sites", FINE),
    ("dual_runs_objectgrid", "object_grid", "counties", COARSE),
    ("onestep_pip", "onestep_pip", "counties", COARSE),
    ("onestep_neighbours", "onestep_neighbours", "sites", FINE),
    ("onestep_neighbours_ponds", "onestep_neighbours", "ponds", FINE),
):
    query(_name, _runs_sql(_layer, _order))(lambda spark, d, m=_method, x=_layer, o=_order: exploded(approximate.build_dual(layer(spark, d, x), GridSpec(o), m)))


@query("onestep_dataframe", _runs_sql("sites", FINE))
def _(spark, d):
    return cells.onestep(layer(spark, d, "sites"), GridSpec(FINE))


@query("coverage_area", f"WITH {duckdb_layer('sites')}, {oracle.edges('sites')} SELECT oid, CAST(abs(sum(x0 * y1 - x1 * y0)) AS BIGINT) AS area2 FROM sites_e GROUP BY oid")
def _(spark, d):
    """Twice the area, from the covered shares of all cells: the shares must add up to the polygon."""
    s = 1 << (DOMAIN_BITS - FINE)
    got = approximate.coverage_cells(layer(spark, d, "sites"), GridSpec(FINE))
    return got.groupBy("oid").agg(F.round(F.sum("coverage") * (2 * s * s)).cast("long").alias("area2"))


_TYPES = f"WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)}, {oracle.types('sites')}"


@query("coverage_cells", f"{_TYPES} SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS hid, type FROM sites_types")
def _(spark, d):
    return approximate.coverage_cells(layer(spark, d, "sites"), GridSpec(FINE)).select("oid", "hid", "type")


for _side in "RS":
    _code = " ".join(f"WHEN {k} THEN {v}" for k, v in approximate.CODES[_side].items())
    query(f"coded_run_codes_{_side.lower()}", f"{_TYPES} SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS hid, CASE type {_code} END AS code FROM sites_types")(lambda spark, d, s=_side: approximate.cell_codes(approximate.build_coded(layer(spark, d, "sites"), GridSpec(FINE), s)))


@query("coded_codes_inflated", f"{_TYPES} SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS hid, CASE type {' '.join(f'WHEN {k} THEN {v}' for k, v in approximate.CODES['R'].items())} END AS code FROM sites_types")
def _(spark, d):
    """Codes of all cells, read back from compressed coded runs."""
    return approximate.cell_codes(approximate.build_coded(layer(spark, d, "sites"), GridSpec(FINE), compressed=True))


@query("coded_runs", _runs_sql("sites", FINE).replace("SELECT oid, list, min(h) AS st, max(h) + 1 AS en FROM marked GROUP BY oid, list, g", "SELECT oid, min(h) AS st, max(h) + 1 AS en FROM marked WHERE list = 'cover' GROUP BY oid, g"))
def _(spark, d):
    coded = approximate.build_coded(layer(spark, d, "sites"), GridSpec(FINE))
    return exploded(coded.select("oid", F.col("runs").alias("cover"), F.col("runs").alias("core"))).where("list = 'cover'").drop("list")


_RASTER = f"WITH {duckdb_layer('sites')}, {oracle.cells('sites', None)}, {oracle.types('sites')}"


@query("local_raster", f"{_RASTER} SELECT oid, k::BIGINT AS k, cx, cy, type::BIGINT AS type FROM sites_types JOIN sites_s USING (oid)")
def _(spark, d):
    got = approximate.build_local_raster(layer(spark, d, "sites"))
    return got.select("oid", F.col("k").cast("long").alias("k"), F.explode("cells").alias("c")).select("oid", "k", "c.cx", "c.cy", F.col("c.type").cast("long").alias("type"))


@query("local_raster_level", f"WITH {duckdb_layer('counties')} SELECT oid, (SELECT min(k) FROM range(22) t(k) WHERE (xmax // (1::BIGINT << k) - xmin // (1::BIGINT << k) + 1) * (ymax // (1::BIGINT << k) - ymin // (1::BIGINT << k) + 1) <= 750) AS k FROM counties")
def _(spark, d):
    return approximate.raster_level(layer(spark, d, "counties")).select("oid", F.col("k").cast("long").alias("k"))


@query("corner_hull", f"WITH {duckdb_layer('sites')}, {oracle.hulls('sites')} SELECT oid, least(count(*), 5) AS n_corners, count(*) AS n_hull, 0::BIGINT AS n_outside FROM sites_hull GROUP BY oid")
def _(spark, d):
    """At most five corners, around all corners of the hull (none lies outside)."""
    got = approximate.build_corner_hull(layer(spark, d, "sites"))
    n = F.size("corners") / 2

    def corner(i):
        j = (F.pmod(i, n) * 2).cast("int")
        return F.get("corners", j), F.get("corners", j + 1)

    def outside(i, j):
        (ax, ay), (bx, by) = corner(i), corner(i + 1)
        x, y = F.get("hull", j * 2), F.get("hull", j * 2 + 1)
        return (bx - ax) * (y - ay) - (by - ay) * (x - ax) < -1e-3

    out = F.size(F.filter(F.sequence(F.lit(0), (F.size("hull") / 2 - 1).cast("int")), lambda j: F.exists(F.sequence(F.lit(0), (n - 1).cast("int")), lambda i: outside(i, j))))
    return got.select("oid", n.cast("long").alias("n_corners"), (F.size("hull") / 2).cast("long").alias("n_hull"), out.cast("long").alias("n_outside"))


@query("convex_hull", f"""WITH {duckdb_layer('sites')}, p AS (SELECT DISTINCT oid, x, y FROM sites_v),
side AS (SELECT a.oid, a.x, a.y, b.x AS bx, b.y AS qy FROM p a JOIN p b ON a.oid = b.oid AND (a.x, a.y) <> (b.x, b.y)),
good AS (SELECT s.oid, s.x, s.y, s.bx, s.qy FROM side s JOIN p c ON c.oid = s.oid GROUP BY ALL
 HAVING bool_and((s.bx - s.x) * (c.y - s.y) - (s.qy - s.y) * (c.x - s.x) >= 0)),
tips AS (SELECT oid, x, y, max((bx - x) * (bx - x) + (qy - y) * (qy - y)) AS m FROM good GROUP BY ALL)
SELECT oid, x, y FROM tips t WHERE NOT EXISTS (SELECT 1 FROM p a JOIN p b ON a.oid = b.oid WHERE a.oid = t.oid AND (a.x, a.y) <> (t.x, t.y) AND (b.x, b.y) <> (t.x, t.y)
 AND (b.x - a.x) * (t.y - a.y) = (b.y - a.y) * (t.x - a.x) AND (a.x - t.x) * (b.x - t.x) + (a.y - t.y) * (b.y - t.y) < 0)""")
def _(spark, d):
    hull = approximate.build_corner_hull(layer(spark, d, "sites"))
    flat = hull.select("oid", "hull", F.explode(F.sequence(F.lit(0), (F.size("hull") / 2 - 1).cast("int"))).alias("i"))
    return flat.select("oid", F.get("hull", F.col("i") * 2).alias("x"), F.get("hull", F.col("i") * 2 + 1).alias("y"))


@query("line_cells", f"WITH {duckdb_layer('tracks')}, {oracle.cells('tracks', 12, False)} SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', 12)} AS hid FROM tracks_edge")
def _(spark, d):
    return approximate.build_line_cells(layer(spark, d, "tracks"), GridSpec(12)).select("oid", F.explode("cells").alias("hid"))


@query("line_runs", f"""WITH {duckdb_layer('tracks')}, {oracle.cells('tracks', 12, False)}, ids AS (SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', 12)} AS h FROM tracks_edge),
m AS (SELECT *, h - row_number() OVER (PARTITION BY oid ORDER BY h) AS g FROM ids) SELECT oid, min(h) AS st, max(h) + 1 AS en FROM m GROUP BY oid, g""")
def _(spark, d):
    got = approximate.build_line_cells(layer(spark, d, "tracks"), GridSpec(12), as_runs=True)
    return exploded(got.select("oid", F.col("cells").alias("cover"), F.col("cells").alias("core"))).where("list = 'cover'").drop("list")


@query("selection_prep", _runs_sql("counties", COARSE).replace("FROM marked GROUP", "FROM marked WHERE oid = (SELECT min(oid) FROM counties) GROUP"))
def _(spark, d):
    first = layer(spark, d, "counties").orderBy("oid").select("oid", "ring").first()
    got = join.approximate_query(spark, [(p.x, p.y) for p in first.ring], GridSpec(COARSE))
    return exploded(got.withColumn("oid", F.lit(first.oid)))


@query("layer_mbr", f"WITH {duckdb_layer('provinces')} SELECT oid, xmin, ymin, xmax, ymax, n AS n_vertices FROM provinces")
def _(spark, d):
    return layer(spark, d, "provinces").select("oid", *tiles.BOX, F.col("n_vertices").cast("long").alias("n_vertices"))


# ---- filters and joins ----

PAIRS = {"sites_ponds": ("sites", "ponds", FINE), "sites_counties": ("sites", "counties", COARSE)}
_COUNT = " SELECT verdict, count(*) AS n FROM verdicts GROUP BY verdict"
_ALL = " SELECT rid, sid, verdict FROM verdicts"
_SHARE = " SELECT verdict, count(*) AS n, count(*) * 10000 // (SELECT count(*) FROM verdicts) AS bp FROM verdicts GROUP BY verdict"


def _join(spark, d, pair: str, **k) -> join.JoinResult:
    r, s, order = PAIRS[pair]
    return join.spatial_join(layer(spark, d, r), layer(spark, d, s), grid=GridSpec(order), **k)


def _verdicts(spark, d, r: str, s: str, order: int, predicate: str = "intersects", mbr_predicate: str | None = None, **k) -> DataFrame:
    a, b = layer(spark, d, r), layer(spark, d, s)
    boxes = mbr_predicate or ("within" if predicate == "within" else "intersects")
    if predicate != "line":
        return join.box_verdicts(a, b, predicate, grid=GridSpec(order), boxes=boxes, **k)
    pairs = mbr.mbr_join(a, b, boxes).drop("tile_id")
    return join.verdicts(pairs, a, b, predicate, grid=GridSpec(order), **k)


for _p, (_r, _s, _o) in PAIRS.items():
    _dual = oracle.dual_verdicts(_r, _s, _o)
    query(f"dual_filter_{_p}", _dual + _ALL)(lambda spark, d, p=_p: _verdicts(spark, d, *PAIRS[p]).select("rid", "sid", "verdict"))
    query(f"dual_filter_compressed_{_p}", _dual + _ALL)(lambda spark, d, p=_p: _verdicts(spark, d, *PAIRS[p], method="dual_compressed").select("rid", "sid", "verdict"))
    query(f"effectiveness_dual_{_p}", _dual + _SHARE)(lambda spark, d, p=_p: _join(spark, d, p).stats())
    _exact = oracle.exact_intersects(_r, _s) + " SELECT rid, sid FROM result"
    for _m in join.METHODS:
        query(f"join_{_m}_{_p}", _exact)(lambda spark, d, p=_p, m=_m: _pairs(_join(spark, d, p, method=m)))
    query(f"partitioned_join_{_p}", _exact)(lambda spark, d, p=_p: _pairs(join.partitioned_join(layer(spark, d, PAIRS[p][0]), layer(spark, d, PAIRS[p][1]), 3, 10)))
    query(f"mixed_order_join_{_p}", _exact)(lambda spark, d, p=_p: _pairs(join.spatial_join(layer(spark, d, PAIRS[p][0]), layer(spark, d, PAIRS[p][1]), order_left=PAIRS[p][2], order_right=PAIRS[p][2] - 2)))
    query(f"quadtree_join_{_p}", _exact)(lambda spark, d, p=_p: _quadtree(spark, d, p))
    query(f"refine_intersects_{_p}", _exact)(lambda spark, d, p=_p: refine(mbr.mbr_join(layer(spark, d, PAIRS[p][0]), layer(spark, d, PAIRS[p][1])), layer(spark, d, PAIRS[p][0]), layer(spark, d, PAIRS[p][1])))
    for _m in ("coded", "local_raster", "corner_hull", "direct"):
        query(f"effectiveness_{_m}_{_p}", oracle.method_verdicts(_r, _s, _m, _o) + _SHARE)(lambda spark, d, p=_p, m=_m: _join(spark, d, p, method=m).stats())


def _quadtree(spark, d, p: str) -> DataFrame:
    a, b = (layer(spark, d, x) for x in PAIRS[p][:2])
    return _pairs(join.spatial_join(a, b, grid=GridSpec(PAIRS[p][2]), tiles=tiles.quadtree_tiles([a, b], 500)))


@query("dual_filter_orders", " UNION ALL ".join(f"SELECT '{_o}' AS merge_order, * FROM ({oracle.dual_verdicts('sites', 'ponds', FINE, merge_order=_o)} SELECT verdict, count(*) AS n, CAST(sum(merges) AS BIGINT) AS merges FROM verdicts GROUP BY verdict)" for _o in filters.ORDERS))
def _(spark, d):
    """Merges performed and verdicts for each merge order: verdicts agree, merges don't."""
    r, s, order = PAIRS["sites_ponds"]
    return join.order_counts(layer(spark, d, r), layer(spark, d, s), GridSpec(order)).select("verdict", "n", "merges", "merge_order")


for _i, _order in enumerate(filters.ORDERS):
    query(f"dual_filter_order_{_i}", oracle.dual_verdicts("sites", "counties", COARSE) + _COUNT)(lambda spark, d, o=_order: _verdicts(spark, d, *PAIRS["sites_counties"], merge_order=o).groupBy("verdict").agg(F.count(F.lit(1)).alias("n")))


@query("dual_filter_auto", oracle.dual_verdicts("sites", "counties", COARSE) + _COUNT)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], merge_order="auto").groupBy("verdict").agg(F.count(F.lit(1)).alias("n"))


@query("dual_filter_incremental", oracle.dual_verdicts("sites", "counties", COARSE) + _ALL)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], method="dual_compressed", incremental=True).select("rid", "sid", "verdict")


@query("runs_overlap", oracle.dual_verdicts("sites", "counties", COARSE) + " SELECT rid, sid FROM verdicts WHERE verdict <> 'miss'")
def _(spark, d):
    """The cover-cover merge, relationally: runs as intervals in blocks of the curve."""
    a, b = (layer(spark, d, x) for x in ("sites", "counties"))
    r, s = (exploded(approximate.build_dual(x, GridSpec(COARSE))).where("list = 'cover'") for x in (a, b))
    pairs = mbr.mbr_join(a, b).select("rid", "sid")
    return cells.interval_join(r, s).join(pairs, ["rid", "sid"], "left_semi").distinct()


@query("coded_filter_cells", oracle.coded_verdicts('sites', 'counties', COARSE) + _ALL)
def _(spark, d):
    """The coded filter as a relation: equal cells joined, codes compared by bit_and."""
    return cells.coded_verdicts_relational(mbr.mbr_join(layer(spark, d, "sites"), layer(spark, d, "counties")), *(approximate.coverage_cells(layer(spark, d, x), GridSpec(COARSE)) for x in ("sites", "counties")))


@query("coded_filter", oracle.coded_verdicts('sites', 'counties', COARSE) + _ALL)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], method="coded").select("rid", "sid", "verdict")


@query("coded_filter_compressed", oracle.coded_verdicts('sites', 'counties', COARSE) + _ALL)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], method="coded_compressed").select("rid", "sid", "verdict")


@query("coded_filter_swapped", oracle.coded_verdicts('sites', 'counties', COARSE) + _ALL)
def _(spark, d):
    a, b = (layer(spark, d, x) for x in ("sites", "counties"))
    coded = [approximate.build_coded(x, GridSpec(COARSE), "R") for x in (a, b)]
    return filters.coded_filter(mbr.mbr_join(a, b).drop("tile_id"), *coded, same_side=True).select("rid", "sid", "verdict")


@query("coded_within_filter", oracle.coded_within_verdicts("ponds", "sites", FINE) + _ALL)
def _(spark, d):
    return _verdicts(spark, d, "ponds", "sites", FINE, "within", method="coded").select("rid", "sid", "verdict")


@query("local_raster_filter", oracle.raster_verdicts("sites", "counties") + _ALL)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], method="local_raster").select("rid", "sid", "verdict")


@query("local_raster_upscale", f"{_RASTER}, one AS (SELECT *, 1 AS d FROM sites_types) SELECT oid, cx, cy, type::BIGINT AS type FROM ({oracle.upscaled('one', 'd', 'oid')})")
def _(spark, d):
    return measures.upscaled_types(approximate.build_local_raster(layer(spark, d, "sites")), 1)


@query("corner_hull_filter", oracle.hull_verdicts("sites", "counties") + _ALL)
def _(spark, d):
    return _verdicts(spark, d, *PAIRS["sites_counties"], method="corner_hull").select("rid", "sid", "verdict")


for _a, _b in ((11, 8), (8, 10)):

    @query("dual_filter_mixed_order" if _a > _b else "dual_filter_mixed_order_up", oracle.mixed_verdicts("sites", "counties", _a, _b) + _ALL)
    def _(spark, d, a=_a, b=_b):
        r, s = (layer(spark, d, x) for x in ("sites", "counties"))
        return join.verdicts(mbr.mbr_join(r, s).drop("tile_id"), r, s, order_left=a, order_right=b).select("rid", "sid", "verdict")


WITHIN = {"ponds_sites": ("ponds", "sites", FINE), "sites_counties": ("sites", "counties", COARSE)}
for _p, (_r, _s, _o) in WITHIN.items():
    for _strict in (False, True):
        query(f"dual_within_{'strict' if _strict else 'filter'}_{_p}", oracle.within_verdicts(_r, _s, _o, _strict) + _ALL)(lambda spark, d, a=(_r, _s, _o), x=_strict: _verdicts(spark, d, *a, "within", strict=x).select("rid", "sid", "verdict"))
    for _m in join.METHODS:
        query(f"within_join_{_m}_{_p}", oracle.exact_within(_r, _s) + " SELECT rid, sid FROM result")(lambda spark, d, a=(_r, _s, _o), m=_m: _pairs(join.spatial_join(layer(spark, d, a[0]), layer(spark, d, a[1]), "within", m, GridSpec(a[2]))))
    query(f"local_raster_within_{_p}", oracle.raster_verdicts(_r, _s, "within", True) + _COUNT)(lambda spark, d, a=(_r, _s, _o): _verdicts(spark, d, *a, "within", method="local_raster").groupBy("verdict").agg(F.count(F.lit(1)).alias("n")))
    query(f"corner_hull_within_{_p}", oracle.hull_verdicts(_r, _s, "within", True) + _COUNT)(lambda spark, d, a=(_r, _s, _o): _verdicts(spark, d, *a, "within", method="corner_hull").groupBy("verdict").agg(F.count(F.lit(1)).alias("n")))
query("refine_within", oracle.exact_within("ponds", "sites") + " SELECT rid, sid FROM result")(lambda spark, d: refine(mbr.mbr_join(layer(spark, d, "ponds"), layer(spark, d, "sites"), "within"), layer(spark, d, "ponds"), layer(spark, d, "sites"), "within"))

LINES = {"sites_tracks": ("sites", "tracks", 12), "ponds_tracks": ("ponds", "tracks", 12), "counties_tracks": ("counties", "tracks", COARSE)}
for _p, (_r, _s, _o) in LINES.items():
    query(f"dual_line_filter_{_p}", oracle.line_verdicts(_r, _s, _o) + _ALL)(lambda spark, d, a=(_r, _s, _o): _verdicts(spark, d, *a, "line").select("rid", "sid", "verdict"))
    for _m in ("dual", "corner_hull", "direct"):
        query(f"line_join_{_m}_{_p}", oracle.exact_intersects(_r, _s, True) + " SELECT rid, sid FROM result")(lambda spark, d, a=(_r, _s, _o), m=_m: _pairs(join.spatial_join(layer(spark, d, a[0]), layer(spark, d, a[1]), "line", m, GridSpec(a[2]))))
query("corner_hull_line_filter", oracle.hull_verdicts("counties", "tracks") + _COUNT)(lambda spark, d: _verdicts(spark, d, "counties", "tracks", COARSE, "line", method="corner_hull").groupBy("verdict").agg(F.count(F.lit(1)).alias("n")))
query("refine_line", oracle.exact_intersects("sites", "tracks", True) + " SELECT rid, sid FROM result")(lambda spark, d: refine(mbr.mbr_join(layer(spark, d, "sites"), layer(spark, d, "tracks")), layer(spark, d, "sites"), layer(spark, d, "tracks"), "line"))

_CAND = f"WITH {duckdb_layer('sites')}, {duckdb_layer('ponds')}, {oracle.candidates('sites', 'ponds')} SELECT rid, sid FROM cand"
for _st in ("tiled", "sweep", "broadcast", "nested"):
    query(f"mbr_join_{_st}", _CAND)(lambda spark, d, s=_st: mbr.mbr_join(layer(spark, d, "sites"), layer(spark, d, "ponds"), strategy=s).select("rid", "sid"))
query("mbr_within_join", f"WITH {duckdb_layer('ponds')}, {duckdb_layer('sites')}, {oracle.candidates('ponds', 'sites', True)} SELECT rid, sid FROM cand")(lambda spark, d: mbr.mbr_join(layer(spark, d, "ponds"), layer(spark, d, "sites"), "within").select("rid", "sid"))


@query("mbr_join_dedup_free", _CAND.replace("SELECT rid, sid FROM cand", "SELECT count(*) AS pairs, count(*) AS distinct_pairs FROM cand"))
def _(spark, d):
    return mbr.mbr_join(layer(spark, d, "sites"), layer(spark, d, "ponds")).agg(F.count(F.lit(1)).alias("pairs"), F.count_distinct("rid", "sid").alias("distinct_pairs"))


_BOX = (300000, 300000, 420000, 500000)
query("selection_mbr", f"WITH {duckdb_layer('ponds')} SELECT oid FROM ponds WHERE xmin <= {_BOX[2]} AND xmax >= {_BOX[0]} AND ymin <= {_BOX[3]} AND ymax >= {_BOX[1]}")(lambda spark, d: mbr.window(layer(spark, d, "ponds"), _BOX).select("oid"))
for _t in ("sites", "ponds"):
    query(f"selection_join_{_t}", oracle.exact_intersects("probes", _t) + " SELECT rid, sid FROM result")(lambda spark, d, t=_t: _pairs(join.spatial_select(layer(spark, d, t), layer(spark, d, "probes"), grid=GridSpec(COARSE))))
    query(f"selection_query_{_t}", oracle.dual_verdicts("probes", _t, COARSE) + _ALL)(lambda spark, d, t=_t: join.spatial_select(layer(spark, d, t), layer(spark, d, "probes"), grid=GridSpec(COARSE)).verdicts.select("rid", "sid", "verdict"))


@query("point_in_polygon", f"""WITH {duckdb_layer('counties')}, {oracle.edges('counties')}, {duckdb_layer('ponds')}, p AS (SELECT oid AS pid, (xmin + xmax) // 2 AS px, (ymin + ymax) // 2 AS py FROM ponds),
c AS (SELECT pid, px, py, k.oid AS cid FROM p JOIN counties k ON px BETWEEN xmin AND xmax AND py BETWEEN ymin AND ymax)
SELECT pid, cid FROM c JOIN counties_e e ON e.oid = cid WHERE (y0 > py) <> (y1 > py) AND ((x1 - x0) * (py - y0) - (px - x0) * (y1 - y0) > 0) = (y1 > y0) GROUP BY ALL HAVING count(*) % 2 = 1""")
def _(spark, d):
    x, y = F.floor((F.col("xmin") + F.col("xmax")) / 2), F.floor((F.col("ymin") + F.col("ymax")) / 2)
    p = layer(spark, d, "ponds").select("oid", x.alias("px"), y.alias("py"))
    boxes = p.select("oid", F.col("px").alias("xmin"), F.col("py").alias("ymin"), F.col("px").alias("xmax"), F.col("py").alias("ymax"))
    near = mbr.mbr_join(boxes, layer(spark, d, "counties")).select(F.col("rid").alias("oid"), F.col("sid").alias("cid"))
    both = near.join(p, "oid").join(layer(spark, d, "counties").select(F.col("oid").alias("cid"), "ring"), "cid")
    return both.where(cells.inside(F.col("px"), F.col("py"), F.col("ring"))).select(F.col("oid").alias("pid"), "cid")


# ---- codec ----


def _gaps_sql(tail: str) -> str:
    return f"""{_runs_sql('sites', FINE).replace('SELECT oid, list, min(h)', ', runs AS (SELECT oid, list, min(h)')}), ends AS (SELECT oid, list, unnest([st, en]) AS v FROM runs),
g AS (SELECT oid, list, v - coalesce(lag(v) OVER (PARTITION BY oid, list ORDER BY v), 0) AS gap FROM ends) {tail}"""


def _gap_rows(spark, d) -> DataFrame:
    dual = approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE))
    parts = [dual.select("oid", F.lit(c).alias("list"), F.explode(codec.gap_column(F.col(c))).alias("gap")) for c in ("cover", "core")]
    return parts[0].union(parts[1])


query("gap_encode", _gaps_sql("SELECT oid, list, gap FROM g"))(_gap_rows)
query("vbyte_sizes", _gaps_sql("SELECT oid, CAST(sum(1 + (gap >= 128)::INT + (gap >= 16384)::INT + (gap >= 2097152)::INT + (gap >= 268435456)::INT) AS BIGINT) AS bytes FROM g GROUP BY oid"))(lambda spark, d: _gap_rows(spark, d).groupBy("oid").agg(F.sum(codec.vbyte_size(F.col("gap"))).alias("bytes")))


@query("vbyte_encode", _gaps_sql("SELECT oid, CAST(sum(1 + (gap >= 128)::INT + (gap >= 16384)::INT + (gap >= 2097152)::INT + (gap >= 268435456)::INT) AS BIGINT) AS bytes FROM g GROUP BY oid"))
def _(spark, d):
    got = approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE), compressed=True)
    return got.select("oid", (F.length("cover") + F.length("core")).cast("long").alias("bytes"))


query("codec_roundtrip", _runs_sql("sites", FINE))(lambda spark, d: exploded(approximate.decompress(approximate.compress(approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE))))))


# ---- measures ----

query("layer_stats", "WITH " + ", ".join(duckdb_layer(x) for x in ("ponds", "sites", "zones", "counties", "provinces")) + " " + " UNION ALL ".join(f"SELECT '{x}' AS layer, count(*) AS objects, CAST(sum(n) AS BIGINT) AS vertices, CAST(sum((xmax - xmin) * (ymax - ymin)) AS BIGINT) AS box_area FROM {x}" for x in ("ponds", "sites", "zones", "counties", "provinces")))(lambda spark, d: measures.layer_stats({x: layer(spark, d, x) for x in ("ponds", "sites", "zones", "counties", "provinces")}))
query("run_stats", _runs_sql("sites", FINE).replace("SELECT oid, list, min(h)", ", runs AS (SELECT oid, list, min(h)") + """) SELECT oid, count(*) FILTER (WHERE list = 'cover') AS cover_runs, count(*) FILTER (WHERE list = 'core') AS core_runs, CAST(coalesce(sum(en - st) FILTER (WHERE list = 'cover'), 0) AS BIGINT) AS cover_cells, CAST(coalesce(sum(en - st) FILTER (WHERE list = 'core'), 0) AS BIGINT) AS core_cells FROM runs GROUP BY oid""")(lambda spark, d: measures.run_stats(approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE))))
query("pip_counts", f"""WITH RECURSIVE {duckdb_layer('sites')}, {oracle.cells('sites', 12)}, {oracle.gaps('sites', 12)}, {oracle.regions('sites')} SELECT 'onestep_pip' AS method, count(*) AS gaps, count(*) AS tests FROM sites_gap
UNION ALL SELECT 'onestep_neighbours', count(*), count(*) FILTER (WHERE root) FROM sites_gap UNION ALL SELECT 'flood', 0, n FROM sites_regions""")(lambda spark, d: measures.pip_counts(layer(spark, d, "sites"), GridSpec(12)))
query("gap_counts", f"""WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)}, ids AS (SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', FINE)} AS h FROM sites_edge), m AS (SELECT *, h - row_number() OVER (PARTITION BY oid ORDER BY h) AS g FROM ids)
SELECT oid, count(DISTINCT g) - 1 AS n_gaps, count(*) AS n_edge FROM m GROUP BY oid""")(lambda spark, d: approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE), "onestep_pip").select("oid", F.col("n_pip").cast("long").alias("n_gaps"), F.col("n_edge").cast("long").alias("n_edge")))
_SPACE = " UNION ALL ".join(oracle.space(x, FINE) for x in ("ponds", "sites"))
query("space_report", _SPACE)(lambda spark, d: measures.space_report({x: layer(spark, d, x) for x in ("ponds", "sites")}, GridSpec(FINE)))
query("ratio_report", oracle.ratios(_SPACE))(lambda spark, d: measures.ratio_report(measures.space_report({x: layer(spark, d, x) for x in ("ponds", "sites")}, GridSpec(FINE))))
query("line_bytes", f"""WITH {duckdb_layer('tracks')}, {oracle.cells('tracks', 12, False)}, ids AS (SELECT oid, {hilbert.duckdb_hilbert('cx', 'cy', 12)} AS h FROM tracks_edge),
m AS (SELECT *, h - row_number() OVER (PARTITION BY oid ORDER BY h) AS g FROM ids) SELECT oid, 4 * count(*) AS as_cells, 8 * count(DISTINCT g) AS as_runs FROM m GROUP BY oid""")(lambda spark, d: measures.line_bytes(layer(spark, d, "tracks"), GridSpec(12)))


@query("tile_replication", f"WITH {duckdb_layer('counties')}, t AS (SELECT oid, unnest(range(xmin * 4 // {DOMAIN}, xmax * 4 // {DOMAIN} + 1)) AS tx, ymin, ymax FROM counties), u AS (SELECT oid, tx, unnest(range(ymin * 4 // {DOMAIN}, ymax * 4 // {DOMAIN} + 1)) AS ty FROM t) SELECT count(DISTINCT oid) AS objects, count(*) AS replicas, count(DISTINCT tx * 4 + ty) AS tiles FROM u")
def _(spark, d):
    return tiles.replication(layer(spark, d, "counties"), tiles.uniform_tiles(4))


@query("tile_quadtree")
def _(spark, d):
    a = layer(spark, d, "ponds")
    return tiles.replicate(a, tiles.quadtree_tiles([a], 400)).groupBy("tile_id").agg(F.count(F.lit(1)).alias("n"))


@query("choose_order", "WITH " + ", ".join(duckdb_layer(x) for x in ("ponds", "sites", "counties", "provinces")) + " " + " UNION ALL ".join(f"SELECT '{x}' AS layer, coalesce((SELECT max(o) FROM range(1, 17) t(o) WHERE 2 * (SELECT avg((xmax - xmin) + (ymax - ymin)) FROM {x}) / ({DOMAIN} >> o) <= 2000), 1)::INT AS order_" for x in ("ponds", "sites", "counties", "provinces")))
def _(spark, d):
    return spark.createDataFrame([(x, join.choose_order(layer(spark, d, x), 2000)) for x in ("ponds", "sites", "counties", "provinces")], "layer string, order_ int")


# ---- sources ----


@query("wkt_roundtrip", f"WITH {duckdb_layer('sites')} SELECT oid, i, x, y FROM sites_v")
def _(spark, d):
    text = layer(spark, d, "sites").select("oid", wkt.to_wkt(F.col("ring"), True).alias("wkt"))
    return text.select("oid", F.posexplode(wkt.from_wkt(F.col("wkt"))).alias("i", "p")).select("oid", F.col("i").cast("long").alias("i"), "p.x", "p.y")


@query("scan_mbr_pruned", SQL["selection_mbr"])
def _(spark, d):
    """The window over the stored layer, sorted by box corner: row groups outside it are skipped."""
    path = shared_file(spark, "layer")
    store.write_layer(layer(spark, d, "ponds"), path)
    return mbr.window(store.read_layer(spark, path), _BOX).select("oid")


@query("scan_pruned_lists", _runs_sql("sites", FINE).replace("SELECT oid, list, min(h)", ", runs AS (SELECT oid, list, min(h)") + ") SELECT oid, count(*) AS n FROM runs WHERE list = 'cover' GROUP BY oid")
def _(spark, d):
    stored = materialize(approximate.build_dual(layer(spark, d, "sites"), GridSpec(FINE)))
    return stored.select("oid", (F.size("cover") / 2).cast("long").alias("n"))


@query("unnest_ring", f"WITH {duckdb_layer('sites')} SELECT oid, x, y FROM sites_v")
def _(spark, d):
    return layer(spark, d, "sites").select("oid", F.explode("ring").alias("p")).select("oid", "p.x", "p.y")


@query("posexplode_edges", f"WITH {duckdb_layer('sites')}, {oracle.edges('sites')} SELECT oid, x0, y0, x1, y1 FROM sites_e")
def _(spark, d):
    return cells.ring_edges(layer(spark, d, "sites")).select("oid", "x0", "y0", "x1", "y1")


@query("collect_ring", f"WITH {duckdb_layer('sites')} SELECT oid, string_agg(x || ' ' || y, ',' ORDER BY i) AS points FROM sites_v GROUP BY oid")
def _(spark, d):
    v = layer(spark, d, "sites").select("oid", F.posexplode("ring").alias("i", "p"))
    ring = F.array_sort(F.collect_list(F.struct("i", "p")))
    return v.groupBy("oid").agg(ring.alias("r")).select("oid", F.array_join(F.transform("r", lambda e: F.concat_ws(" ", e["p"]["x"], e["p"]["y"])), ",").alias("points"))


@query("join_blobs_sites")
def _(spark, d):
    """Spiky stars with sites: the dual filter on irregular shapes, then the exact test."""
    return join.spatial_join(layer(spark, d, "blobs"), layer(spark, d, "sites"), grid=GridSpec(COARSE)).pairs.select("rid", "sid")
