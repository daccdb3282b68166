"""Cells and runs as DataFrames: the optimizer-visible forms of traversal, fill and one-step construction.

The Arrow kernels in ``approximate`` do the same per batch without a shuffle;
these forms serve ad-hoc SQL users and check the kernels.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rasterruns.functions import hilbert
from rasterruns.grid import GridSpec

#: Codes of weak, strong and full cells, left-hand and right-hand.
LEFT_CODES, RIGHT_CODES = (0b100, 0b101, 0b011), (0b010, 0b011, 0b101)


def ring_edges(layer: DataFrame, points: str = "ring", closed: bool = True) -> DataFrame:
    """``(oid, x0, y0, x1, y1)``, one row an edge; no shuffle."""
    n = F.size(points)
    following = F.get(F.col(points), (F.col("i") + 1) % n)
    e = layer.select("oid", points, F.posexplode(points).alias("i", "p")).withColumn("q", following)
    e = e if closed else e.where(F.col("i") + 1 < n)
    return e.select("oid", F.col("p.x").alias("x0"), F.col("p.y").alias("y0"), F.col("q.x").alias("x1"), F.col("q.y").alias("y1"))


def _div(a: Column, b: Column) -> Column:
    return F.call_function("div", a, b)


def edge_cells(layer: DataFrame, grid: GridSpec, points: str = "ring", closed: bool = True) -> DataFrame:
    """``(oid, cx, cy, hid)``: edges cut into column strips, strips into rows, then distinct cells."""
    s, c = grid.cell, F.col
    e = ring_edges(layer, points, closed)
    e = e.select("oid", *[(F.when(c("x0") <= c("x1"), c(a)).otherwise(c(b)) - o).alias(n) for a, b, n, o in (("x0", "x1", "xa", grid.x0), ("y0", "y1", "ya", grid.y0), ("x1", "x0", "xb", grid.x0), ("y1", "y0", "yb", grid.y0))])
    e = e.withColumn("cx", F.explode(F.sequence(_div(c("xa"), F.lit(s)), _div(c("xb"), F.lit(s)))))
    dx, dy = c("xb") - c("xa"), c("yb") - c("ya")
    left, right = F.greatest(c("xa"), c("cx") * s), F.least(c("xb"), (c("cx") + 1) * s)
    e = e.withColumn("na", c("ya") * dx + (left - c("xa")) * dy).withColumn("nb", c("ya") * dx + (right - c("xa")) * dy).withColumn("q", F.greatest(dx, F.lit(1)) * s).withColumn("open", right == (c("cx") + 1) * s)
    low = F.when(dx == 0, _div(F.least("ya", "yb"), F.lit(s))).when(dy >= 0, _div(c("na"), c("q"))).otherwise(_div(c("nb"), c("q")))
    high = F.when(dx == 0, _div(F.greatest("ya", "yb"), F.lit(s))).when(dy < 0, _div(c("na"), c("q"))).when(c("open"), F.greatest(_div(c("na"), c("q")), _div(c("nb") - 1, c("q")))).otherwise(_div(c("nb"), c("q")))
    e = e.select("oid", "cx", F.explode(F.sequence(low, high)).alias("cy")).dropDuplicates(["oid", "cx", "cy"])
    return e.withColumn("hid", hilbert.hilbert_id(c("cx"), c("cy"), grid.order))


def scanline_core(layer: DataFrame, grid: GridSpec) -> DataFrame:
    """``(oid, cx, cy)`` of core cells: crossings of each row's centre line, paired in order, less edge cells."""
    s, c = grid.cell, F.col
    e = ring_edges(layer).where("y0 <> y1")
    up = c("y0") < c("y1")
    e = e.select("oid", *[F.when(up, c(a)).otherwise(c(b)).alias(n) for a, b, n in (("x0", "x1", "xa"), ("y0", "y1", "ya"), ("x1", "x0", "xb"), ("y1", "y0", "yb"))])
    first = lambda y: _div(2 * (y + s) - s - 1, F.lit(2 * s))  # noqa: E731  least row whose centre is at y or above
    e = e.withColumn("lo", first(c("ya"))).withColumn("hi", first(c("yb")) - 1).where("lo <= hi").withColumn("cy", F.explode(F.sequence("lo", "hi")))
    dy = 2 * (c("yb") - c("ya"))
    x = c("xa") * dy + (2 * c("cy") * s + s - 2 * c("ya")) * (c("xb") - c("xa"))  # times dy
    col = _div(2 * x - s * dy + 2 * s * dy, 2 * s * dy)  # floor + 1; operands stay positive inside the domain
    line = Window.partitionBy("oid", "cy").orderBy("col")
    e = e.select("oid", "cy", col.alias("col")).withColumn("n", F.row_number().over(line)).withColumn("end", F.lead("col").over(line))
    spans = e.where((c("n") % 2 == 1) & (c("col") < c("end"))).select("oid", F.explode(F.sequence("col", c("end") - 1)).alias("cx"), "cy")
    return spans.join(edge_cells(layer, grid).select("oid", "cx", "cy"), ["oid", "cx", "cy"], "left_anti")


def to_runs(ids: DataFrame) -> DataFrame:
    """``(oid, hid)`` -> maximal runs ``(oid, st, en)``: gaps and islands."""
    line = Window.partitionBy("oid").orderBy("hid")
    m = ids.select("oid", "hid").withColumn("g", F.col("hid") - F.row_number().over(line))
    return m.groupBy("oid", "g").agg(F.min("hid").alias("st"), (F.max("hid") + 1).alias("en")).drop("g")


def explode_runs(runs: DataFrame) -> DataFrame:
    return runs.select("oid", F.explode(F.sequence("st", F.col("en") - 1)).alias("hid"))


def inside(px: Column, py: Column, ring: Column) -> Column:
    """Even-odd test as an expression over the ring's edges."""
    n = F.size(ring)

    def crosses(i: Column) -> Column:
        a, b = F.get(ring, i), F.get(ring, (i + 1) % n)
        side = (b["x"] - a["x"]) * (py - a["y"]) - (px - a["x"]) * (b["y"] - a["y"])
        return ((a["y"] > py) != (b["y"] > py)) & ((side > 0) == (b["y"] > a["y"]))

    return F.size(F.filter(F.sequence(F.lit(0), n - 1), crosses)) % 2 == 1


def onestep(layer: DataFrame, grid: GridSpec) -> DataFrame:
    """Dual runs ``(oid, list, st, en)`` from sorted edge cells, with a centre test for every gap.

    One shuffle by object: gaps from a window over the curve, each tested
    against its ring, then islands over edge runs and core gaps.
    """
    s, c = grid.cell, F.col
    line = Window.partitionBy("oid").orderBy("hid")
    e = edge_cells(layer, grid).select("oid", "hid").withColumn("nxt", F.lead("hid").over(line))
    gaps = e.where(c("nxt") > c("hid") + 1).select("oid", (c("hid") + 1).alias("st"), c("nxt").alias("en"))
    cell = hilbert.hilbert_cell(c("st"), grid.order)
    gaps = gaps.withColumn("c", cell).join(layer.select("oid", "ring"), "oid")
    half = s // 2
    core = gaps.where(inside(c("c.cx") * s + half, c("c.cy") * s + half, c("ring"))).select("oid", "st", "en")
    parts = to_runs(e).unionByName(core)
    order = Window.partitionBy("oid").orderBy("st")
    m = parts.withColumn("new", F.coalesce((c("st") != F.lag("en").over(order)), F.lit(True)).cast("int")).withColumn("g", F.sum("new").over(order))
    cover = m.groupBy("oid", "g").agg(F.min("st").alias("st"), F.max("en").alias("en"))
    return cover.select("oid", F.lit("cover").alias("list"), "st", "en").union(core.select("oid", F.lit("core").alias("list"), "st", "en"))


def interval_join(r: DataFrame, s: DataFrame, bits: int = 10) -> DataFrame:
    """``(rid, sid)`` for overlapping runs of two relations (oid, st, en): an equi-join on blocks of the curve.

    A pair is reported in the block of the later start only, once for each pair of runs.
    """

    def side(df: DataFrame, p: str) -> DataFrame:
        block = F.explode(F.sequence(F.shiftright("st", bits), F.shiftright(F.col("en") - 1, bits)))
        return df.select(F.col("oid").alias(f"{p}id"), F.col("st").alias(f"{p}st"), F.col("en").alias(f"{p}en"), block.alias("block"))

    both = side(r, "r").join(side(s, "s"), "block").where("rst < sen and sst < ren")
    return both.where(F.shiftright(F.greatest("rst", "sst"), bits) == F.col("block")).select("rid", "sid")


def coded_verdicts_relational(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """The coded filter as a join on equal cells: a shared bit in any cell is a hit."""

    def code(table) -> Column:
        return F.element_at(F.array(*[F.lit(x) for x in table]), F.col("type"))

    r = left.select(F.col("oid").alias("rid"), "hid", code(LEFT_CODES).alias("rc"))
    s = right.select(F.col("oid").alias("sid"), "hid", code(RIGHT_CODES).alias("sc"))
    met = pairs.select("rid", "sid").join(r, "rid").join(s, ["sid", "hid"]).groupBy("rid", "sid").agg(F.bool_or(F.col("rc").bitwiseAND(F.col("sc")) != 0).alias("sure"))
    verdict = F.when(F.col("sure").isNull(), "miss").when(F.col("sure"), "hit").otherwise("unsure")
    return pairs.select("rid", "sid").join(met, ["rid", "sid"], "left").select("rid", "sid", verdict.alias("verdict"))
