"""The paper's experiment workloads on the derived layers, as queries.

Times are left to bench.py; these return what can be compared exactly:
verdict counts, merges, tests, bytes.  ``share`` columns are basis points.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rasterruns.grid import GridSpec
from rasterruns.operators import approximate, filters, mbr, measures, tiles
from rasterruns.plans import join
from rasterruns.queries import oracle
from rasterruns.queries.spatial import COARSE, FINE, layer
from rasterruns.sources.layers import duckdb_layer

Q: dict = {}
SQL: dict = {}
REGIONS = 5
#: Orders that separate the methods at our sizes (order 16 settles nearly all pairs).
ORDERS = (8, 10, 11, 12, 14)
POLYGONS = ("ponds", "sites", "zones", "counties", "provinces", "lakes", "parks")
#: Orders of the constructions, coarser for larger objects, as some keep every cell.
BUILD_ORDERS = {"sites": 11, "ponds": 12, "counties": 9, "zones": 10, "provinces": 8, "lakes": 12, "parks": 11}


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def shares(verdicts: DataFrame, **labels) -> DataFrame:
    """Verdict counts with their share of all candidates, under labels."""
    n = verdicts.groupBy("verdict").agg(F.count(F.lit(1)).alias("n"), F.sum("merges").alias("merges"))
    total = F.sum("n").over(Window.partitionBy(F.lit(0)))  # over one row a verdict
    out = n.select("verdict", "n", "merges", F.floor(F.col("n") * 10000 / total).cast("long").alias("share"))
    return out.select(*[F.lit(v).alias(k) for k, v in labels.items()], *out.columns)


def _union(parts) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({x})" for x in parts)


def _filtered(spark, d, r: str, s: str, method: str, order: int = 16, predicate: str = "intersects", **k) -> DataFrame:
    a, b = (layer(spark, d, x) if isinstance(x, str) else x for x in (r, s))
    boxes = k.pop("boxes", "intersects")
    if predicate != "line":
        return join.box_verdicts(a, b, predicate, method, GridSpec(order), boxes, **k)
    pairs = mbr.mbr_join(a, b, boxes)
    return join.verdicts(pairs.drop("tile_id"), a, b, predicate, method, GridSpec(order), **k)


@_query("w1_layers", "WITH " + ", ".join(duckdb_layer(x) for x in POLYGONS) + " " + " UNION ALL ".join(f"SELECT '{x}' AS layer, count(*) AS objects, CAST(sum(n) AS BIGINT) AS vertices, CAST(sum((xmax - xmin) * (ymax - ymin)) AS BIGINT) AS box_area FROM {x}" for x in POLYGONS))
def _(spark, d):
    """Statistics of all layers."""
    return measures.layer_stats({x: layer(spark, d, x) for x in POLYGONS})


# The tables of the larger experiments are split by layer or pair, so that each comparison stays small.
for _x in POLYGONS:

    @_query(f"w1_space_{_x}", oracle.space(_x, 12))
    def _(spark, d, x=_x):
        """Bytes of every representation."""
        return measures.space_report({x: layer(spark, d, x)}, GridSpec(12))


@_query("w2_order_effect", _union(oracle.shares(oracle.method_verdicts("sites", "ponds", m, o), method=m, grid_order=o) for m in ("coded", "dual") for o in ORDERS))
def _(spark, d):
    """Effect of the grid order, coded and dual, sites with ponds."""
    return _all([shares(_filtered(spark, d, "sites", "ponds", m, o), method=m, grid_order=o) for m in ("coded", "dual") for o in ORDERS])


for _o in (8, 10, 11):
    _query(f"w2_dual_order_{_o}", oracle.dual_verdicts("sites", "ponds", _o) + " SELECT verdict, count(*) AS n FROM verdicts GROUP BY verdict")(lambda spark, d, o=_o: _filtered(spark, d, "sites", "ponds", "dual", o).groupBy("verdict").agg(F.count(F.lit(1)).alias("n")))


def _order_space_sql(name: str, o: int) -> str:
    lists = f"WITH {duckdb_layer(name)}, {oracle.cells(name, o)}, {oracle.gap_lists(name, o)}, {oracle.list_bytes(name)}"
    return f"""{lists} SELECT '{name}' AS layer, 'dual' AS kind, {o} AS grid_order, CAST(sum(4 * ends) AS BIGINT) AS bytes, (SELECT count(*) FROM {name}_gap WHERE root) AS tests FROM {name}_bytes
UNION ALL SELECT '{name}', 'coded', {o}, CAST(sum(4 * ends + code) AS BIGINT), 0 FROM {name}_bytes WHERE list = 'cover'"""


@_query("w3_order_space", _union(_order_space_sql(x, o) for x in ("sites", "ponds") for o in ORDERS))
def _(spark, d):
    """Effect of the grid order on list sizes and centre tests, dual and coded."""
    out = []
    for name in ("sites", "ponds"):
        for o in ORDERS:
            x = layer(spark, d, name)
            label = lambda kind, name=name, o=o: [F.lit(name).alias("layer"), F.lit(kind).alias("kind"), F.lit(o).alias("grid_order")]
            out.append(approximate.build_dual(x, GridSpec(o)).agg(*label("dual"), F.sum(4 * (F.size("cover") + F.size("core"))).alias("bytes"), F.sum("n_pip").alias("tests")))
            out.append(approximate.build_coded(x, GridSpec(o)).agg(*label("coded"), F.sum(4 * F.size("runs") + F.length("code")).alias("bytes"), F.lit(0).cast("long").alias("tests")))
    return _all(out)


@_query("w4_merge_order", _union(oracle.shares(oracle.dual_verdicts("sites", s, o, merge_order=m), pair=f"sites-{s}", merge_order=m) for s, o in (("ponds", 12), ("counties", 11)) for m in filters.ORDERS[:4]))
def _(spark, d):
    """Merge orders: equal verdicts, unlike numbers of merges."""
    return _all([shares(_filtered(spark, d, "sites", s, "dual", o, merge_order=m), pair=f"sites-{s}", merge_order=m) for s, o in (("ponds", 12), ("counties", 11)) for m in filters.ORDERS[:4]])


def _grp(spark, d, name: str, g: int) -> DataFrame:
    return layer(spark, d, name).where(F.col("grp") == g)


@_query("w5_tiles", _union(oracle.shares(oracle.tiled_verdicts("sites", s, p, 10), pair=f"sites-{s}", tiles=p) for s in ("ponds", "counties") for p in (1, 2, 3, 4)))
def _(spark, d):
    """Tiles per dimension: verdict shares."""
    out = []
    for r, s in (("sites", "ponds"), ("sites", "counties")):
        for p in (1, 2, 3, 4):
            out.append(shares(join.partitioned_join(layer(spark, d, r), layer(spark, d, s), p, 10).verdicts, pair=f"{r}-{s}", tiles=p))
    return _all(out)


@_query("w5_tiles_regions", _union(oracle.shares(oracle.tiled_verdicts("lakes", "parks", p, 10, g), region=g, tiles=p) for g in range(REGIONS) for p in (1, 2, 3, 4)))
def _(spark, d):
    return _all([shares(join.partitioned_join(_grp(spark, d, "lakes", g), _grp(spark, d, "parks", g), p, 10).verdicts, region=g, tiles=p) for g in range(REGIONS) for p in (1, 2, 3, 4)])


for _x in POLYGONS:

    @_query(f"w6_tile_space_{_x}", _union(oracle.tiled_bytes(_x, p, 10) for p in (1, 2, 3, 4)))
    def _(spark, d, name=_x):
        """Tiles per dimension: bytes of the lists."""
        x, out = layer(spark, d, name), []
        for p in (1, 2, 3, 4):
            t = tiles.uniform_tiles(p)
            boxes = tiles.raster_boxes([tiles.replicate(x, t)], 10)
            got = approximate.build_dual(tiles.assign(x, t, boxes))
            out.append(got.agg(F.lit(name).alias("layer"), F.lit(p).alias("tiles"), F.sum(4 * (F.size("cover") + F.size("core"))).alias("bytes")))
        return _all(out)


@_query("w7_mixed_orders", _union(oracle.shares(oracle.mixed_verdicts("sites", "counties", 12, o), right_order=o) for o in (12, 11, 10, 9, 8)))
def _(spark, d):
    """Sites at a fine order with counties at coarser ones."""
    return _all([shares(_filtered(spark, d, "sites", "counties", "dual", order_left=12, order_right=o), right_order=o) for o in (12, 11, 10, 9, 8)])


def _constructions_sql(name: str, o: int) -> str:
    """Ends of the lists from labelled cells; centre tests of each method: gaps, unlabelled gaps, regions, free cells."""
    head = f"WITH RECURSIVE {duckdb_layer(name)}, {oracle.cells(name, o)}, {oracle.run_lists(name, o)}, {oracle.gaps(name, o)}, {oracle.regions(name)}"
    tests = {"clip": "0", "flood": f"(SELECT n FROM {name}_regions)", "scanline": "0", "object_grid": f"(SELECT count(*) FROM {name}_w2 ANTI JOIN {name}_edge USING (oid, cx, cy))", "onestep_pip": f"(SELECT count(*) FROM {name}_gap)", "onestep_neighbours": f"(SELECT count(*) FROM {name}_gap WHERE root)"}
    ends = ", ".join(f"(SELECT 2 * count(*) FROM {name}_runs WHERE list = '{x}') AS {x}_ends" for x in ("cover", "core"))
    return head + " " + " UNION ALL ".join(f"SELECT '{name}' AS layer, '{m}' AS method, {ends}, {n} AS tests" for m, n in tests.items())


@_query("w8_constructions", _union(_constructions_sql(x, o) for x, o in BUILD_ORDERS.items()))
def _(spark, d):
    """All constructions build the same lists; their centre tests differ."""
    out = []
    for name, order in BUILD_ORDERS.items():
        for m in ("clip", "flood", "scanline", "object_grid", "onestep_pip", "onestep_neighbours"):
            got = approximate.build_dual(layer(spark, d, name), GridSpec(order), m)
            out.append(got.agg(F.lit(name).alias("layer"), F.lit(m).alias("method"), F.sum(F.size("cover")).alias("cover_ends"), F.sum(F.size("core")).alias("core_ends"), F.sum("n_pip").alias("tests")))
    return _all(out)


#: The pairs of layers that intersection joins run on: name, sides, group.
_PAIRS = [(f"sites-{s}", "sites", s, None) for s in ("ponds", "counties")] + [(f"lakes-parks-{g}", "lakes", "parks", g) for g in range(REGIONS)]
_KIND = {"dual_compressed": "dual"}


def _pair(spark, d, r: str, s: str, g: int | None) -> list[DataFrame]:
    return [layer(spark, d, x) if g is None else _grp(spark, d, x, g) for x in (r, s)]


def _pairs(spark, d) -> list[tuple[str, DataFrame, DataFrame]]:
    """The pairs of layers that intersection joins run on."""
    return [(n, *_pair(spark, d, r, s, g)) for n, r, s, g in _PAIRS]




for _n, _r, _s, _g in _PAIRS:

    @_query(f"w9_joins_{_n.replace('-', '_')}", _union(oracle.shares(oracle.method_verdicts(_r, _s, _KIND.get(m, m), 11, only=_g), pair=_n, method=m) for m in join.METHODS))
    def _(spark, d, n=_n, r=_r, s=_s, g=_g):
        """Six filters on a pair of layers (two pairs and five regional ones)."""
        a, b = _pair(spark, d, r, s, g)
        return _all([shares(_filtered(spark, d, a, b, m, 11), pair=n, method=m) for m in join.METHODS])


for _g in range(REGIONS):
    _only = lambda name, g=_g: duckdb_layer(name).replace(f" FROM {name}_v GROUP BY oid)", f" FROM {name}_v WHERE grp = {g} GROUP BY oid)")
    _query(f"w9_lakes_parks_{_g}", oracle.exact_intersects("lakes", "parks").replace(duckdb_layer("lakes"), _only("lakes")).replace(duckdb_layer("parks"), _only("parks")) + " SELECT rid, sid FROM result")(lambda spark, d, g=_g: join.spatial_join(_grp(spark, d, "lakes", g), _grp(spark, d, "parks", g), grid=GridSpec(12)).pairs.select("rid", "sid"))


@_query("w10_space_ratios", oracle.ratios(_union(oracle.space(x, 12) for x in POLYGONS)))
def _(spark, d):
    """How many times smaller dual lists are than coded ones, over all layers; time ratios are bench.py's."""
    return measures.ratio_report(measures.space_report({x: layer(spark, d, x) for x in POLYGONS}, GridSpec(12)))


@_query("w10_verdicts", _union(oracle.shares(oracle.method_verdicts(r, s, m, 11, only=g), pair=n, kind=m) for n, r, s, g in _PAIRS for m in ("coded", "dual")))
def _(spark, d):
    """What coded and dual runs settle on all pairs: equal misses, and coded hits contain dual hits."""
    return _all([shares(_filtered(spark, d, a, b, m, 11), pair=n, kind=m) for n, a, b in _pairs(spark, d) for m in ("coded", "dual")])


_SIZES = (("sites", 750), ("zones", 150), ("counties", 150), ("provinces", 150))


for _s, _c in _SIZES:

    @_query(f"w11_size_variance_{_s}", _union(oracle.shares(oracle.method_verdicts("ponds", _s, m, 11, max_cells=_c), pair=f"ponds-{_s}", method=m) for m in ("direct", "local_raster", "corner_hull", "dual")))
    def _(spark, d, s=_s, cells=_c):
        """Ponds with ever larger objects: direct, local raster, corner and hull, dual."""
        return _all([shares(_filtered(spark, d, "ponds", s, m, 11, max_cells=cells), pair=f"ponds-{s}", method=m) for m in ("direct", "local_raster", "corner_hull", "dual")])


_query("w11_ponds_zones", oracle.exact_intersects("ponds", "zones") + " SELECT rid, sid FROM result")(lambda spark, d: join.spatial_join(layer(spark, d, "ponds"), layer(spark, d, "zones"), grid=GridSpec(12)).pairs.select("rid", "sid"))


@_query("w12_selections", _union(oracle.shares(oracle.method_verdicts("probes", x, m, 10), layer=x, method=m) for x in ("sites", "ponds") for m in ("coded", "dual")))
def _(spark, d):
    """Query polygons over two layers, coded and dual."""
    probes = layer(spark, d, "probes")
    return _all([shares(join.spatial_select(layer(spark, d, t), probes, m, GridSpec(10)).verdicts, layer=t, method=m) for t in ("sites", "ponds") for m in ("coded", "dual")])


_WITHIN = (("ponds", "sites", FINE), ("sites", "counties", COARSE), ("ponds", "counties", 10))


for _r, _s, _o in _WITHIN:

    @_query(f"w13_within_{_r}_{_s}", _union(oracle.shares(oracle.method_verdicts(_r, _s, m, _o, "within", b), pair=f"{_r}-{_s}", method=m, boxes=b) for m in ("direct", "corner_hull", "local_raster", "coded", "dual") for b in ("within", "intersects")))
    def _(spark, d, r=_r, s=_s, o=_o):
        """Containment joins by all methods, on containing and on intersecting boxes."""
        return _all([shares(_filtered(spark, d, r, s, m, o, "within", boxes=boxes), pair=f"{r}-{s}", method=m, boxes=boxes) for m in ("direct", "corner_hull", "local_raster", "coded", "dual") for boxes in ("within", "intersects")])


_query("w13_ponds_in_counties", oracle.exact_within("ponds", "counties") + " SELECT rid, sid FROM result")(lambda spark, d: join.spatial_join(layer(spark, d, "ponds"), layer(spark, d, "counties"), "within", grid=GridSpec(11)).pairs.select("rid", "sid"))


_LINES = (("sites", 12), ("ponds", 14), ("counties", 10))


@_query("w14_lines", _union(oracle.shares(oracle.method_verdicts(r, "tracks", m, o, "line"), pair=f"{r}-tracks", method=m) for r, o in _LINES for m in ("direct", "corner_hull", "dual")))
def _(spark, d):
    """Polygons with paths: direct, corner and hull, dual."""
    return _all([shares(_filtered(spark, d, r, "tracks", m, o, "line"), pair=f"{r}-tracks", method=m) for r, o in _LINES for m in ("direct", "corner_hull", "dual")])


def _compression_sql(pair: str, r: str, s: str, g: int | None) -> str:
    """Bytes that each decoding reads: both lists of every merge that is made."""
    o = _decode_order(pair)
    head = f"{oracle.dual_verdicts(r, s, o, only=g)}, " + ", ".join(f"{oracle.run_lists(x, o)}, {oracle.list_bytes(x)}, {x}_z AS (SELECT oid, coalesce(sum({{0}}) FILTER (WHERE list = 'cover'), 0) AS c, coalesce(sum({{0}}) FILTER (WHERE list = 'core'), 0) AS k FROM {x}_bytes GROUP BY oid)" for x in (r, s))
    read = "a.c + b.c + CASE WHEN merges > 1 THEN a.c + b.k ELSE 0 END + CASE WHEN merges > 2 THEN a.k + b.c ELSE 0 END"
    rows = lambda name, size: f"{head.replace('{0}', size)} SELECT '{pair}' AS pair, '{name}' AS decoding, verdict, count(*) AS n, CAST(sum({read}) AS BIGINT) AS bytes FROM verdicts JOIN {r}_z a ON a.oid = rid JOIN {s}_z b ON b.oid = sid GROUP BY verdict"
    return f"SELECT * FROM ({rows('whole', 'bytes')}) UNION ALL SELECT * FROM ({rows('plain', '8 * ends')})"


def _decode_order(pair: str) -> int:
    return 10 if pair == "sites-counties" else 12


@_query("w15_compression", _union(_compression_sql(*x) for x in _PAIRS))
def _(spark, d):
    """Plain lists (8 bytes a run) and compressed ones decoded whole: equal verdicts; bytes that the merges read."""
    out = []
    for pair, a, b in _pairs(spark, d):
        pairs = mbr.mbr_join(a, b).drop("tile_id")
        for name, packed in (("whole", True), ("plain", False)):
            lists = [approximate.build_dual(x, GridSpec(_decode_order(pair)), compressed=packed) for x in (a, b)]
            got = filters.dual_filter(pairs, *lists, compressed=packed)
            out.append(got.groupBy("verdict").agg(F.lit(pair).alias("pair"), F.lit(name).alias("decoding"), F.count(F.lit(1)).alias("n"), F.sum("bytes_decoded").alias("bytes")))
    return _all(out)


@_query("w15_incremental", _union(f"{oracle.dual_verdicts(r, s, _decode_order(n), only=g)} SELECT '{n}' AS pair, verdict, count(*) AS n, TRUE AS reads_less FROM verdicts GROUP BY verdict" for n, r, s, g in _PAIRS))
def _(spark, d):
    """Lists decoded block by block inside the merge: equal verdicts, and never more bytes than whole lists."""
    out = []
    for pair, a, b in _pairs(spark, d):
        pairs = mbr.mbr_join(a, b).drop("tile_id")
        coded = [approximate.build_dual(x, GridSpec(_decode_order(pair)), compressed=True) for x in (a, b)]
        whole, parts = (filters.dual_filter(pairs, *coded, compressed=True, incremental=inc).select("rid", "sid", "verdict", F.col("bytes_decoded").alias(name)) for name, inc in (("whole", False), ("parts", True)))
        both = whole.join(parts, ["rid", "sid", "verdict"])
        out.append(both.groupBy("verdict").agg(F.lit(pair).alias("pair"), F.count(F.lit(1)).alias("n"), F.bool_and(F.col("parts") <= F.col("whole")).alias("reads_less")))
    return _all(out)


def _examples_sql() -> str:
    code = lambda side: "CASE type " + " ".join(f"WHEN {t} THEN {c}" for t, c in approximate.CODES[side].items()) + " END"
    return f"""WITH {duckdb_layer('sites')}, {oracle.cells('sites', FINE)}, {oracle.types('sites')}, c AS (SELECT {code('R')} AS code, {code('S')} AS other FROM sites_types)
SELECT code, other, xor(code, {approximate.SWAP}) = other AS swaps, (code & other) <> 0 AS shares_bit, count(*) AS n FROM c GROUP BY code, other"""


@_query("w16_examples", _examples_sql())
def _(spark, d):
    """Packing, alignment and swapping on all sites: cells' codes read back from both sides' packed lists, XORed and ANDed."""
    r, s = (approximate.cell_codes(approximate.build_coded(layer(spark, d, "sites"), GridSpec(FINE), side)) for side in "RS")
    both = r.join(s.withColumnRenamed("code", "other"), ["oid", "hid"])
    n = both.groupBy("code", "other").agg(F.count(F.lit(1)).alias("n"))
    return n.select("code", "other", (F.col("code").bitwiseXOR(F.lit(approximate.SWAP)) == F.col("other")).alias("swaps"), (F.col("code").bitwiseAND(F.col("other")) != 0).alias("shares_bit"), "n")
