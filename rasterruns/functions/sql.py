"""SQL names of the methods: Arrow-vectorised scalar functions, one aggregate and two table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from rasterruns.functions import codec, geometry, hilbert, lists
from rasterruns.grid import GridSpec
from rasterruns.operators import filters, rasterize

_RING = "array<struct<x:bigint,y:bigint>>"


def _points(ring) -> np.ndarray:
    return np.array([(p["x"], p["y"]) for p in ring], np.int64).reshape(-1, 2)


def _lists(series: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    rows = [np.asarray(x if x is not None else [], np.int64) for x in series]
    return np.concatenate([*rows, np.zeros(0, np.int64)]), np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)


def _scalar(spark: SparkSession, name: str, kind: str, f) -> None:
    spark.udf.register(name, F.pandas_udf(f, kind))


def register(spark: SparkSession) -> None:
    """Register all functions; verdict functions take the flat run lists of both sides."""

    def hilbert_id(cx: pd.Series, cy: pd.Series, order: pd.Series) -> pd.Series:
        out = np.zeros(len(cx), np.int64)
        for o in order.unique():
            at = (order == o).to_numpy()
            out[at] = hilbert.encode(cx[at].to_numpy(), cy[at].to_numpy(), int(o))
        return pd.Series(out)

    def hilbert_cell(hid: pd.Series, order: pd.Series) -> pd.DataFrame:
        x, y = np.zeros(len(hid), np.int64), np.zeros(len(hid), np.int64)
        for o in order.unique():
            at = (order == o).to_numpy()
            x[at], y[at] = hilbert.decode(hid[at].to_numpy(), int(o))
        return pd.DataFrame({"cx": x, "cy": y})

    def runs_overlap(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(lists.overlap(_lists(a), _lists(b)))

    def dual_verdict(rc: pd.Series, rk: pd.Series, sc: pd.Series, sk: pd.Series) -> pd.Series:
        held = {("r", "cover"): _lists(rc), ("r", "core"): _lists(rk), ("s", "cover"): _lists(sc), ("s", "core"): _lists(sk)}
        got, _ = filters.dual_verdicts(lambda side, name, rows: lists.take(held[side, name], rows), len(rc))
        return pd.Series(np.array(["unsure", "hit", "miss"])[got])

    def dual_within_verdict(rc: pd.Series, sc: pd.Series, sk: pd.Series) -> pd.Series:
        r, s, k = _lists(rc), _lists(sc), _lists(sk)
        out = np.where(lists.contained(r, k), "hit", "unsure")
        return pd.Series(np.where(lists.overlap(r, s), out, "miss"))

    def coded_verdict(rr: pd.Series, rcode: pd.Series, sr: pd.Series, scode: pd.Series) -> pd.Series:
        sides = [(lists.to_column(*_lists(runs)), pa.array(list(code), pa.binary())) for runs, code in ((rr, rcode), (sr, scode))]
        hit, some = np.zeros(len(rr), bool), np.zeros(len(rr), bool)
        for row, r, s, _ in filters.common_words(*sides):
            some[row] = True
            hit[row[(r & s) != 0]] = True
        return pd.Series(np.where(hit, "hit", np.where(some, "unsure", "miss")))

    def aligned_and(a: pd.Series, b: pd.Series, shift: pd.Series, bits: pd.Series) -> pd.Series:
        return pd.Series([filters.aligned_and(x, y, int(s), int(n)) for x, y, s, n in zip(a, b, shift, bits, strict=True)])

    def vbyte_encode(values: pd.Series) -> pd.Series:
        return pd.Series(codec.encode(*_lists(values)).to_pylist())

    def vbyte_decode(data: pd.Series) -> pd.Series:
        v, o = codec.decode(pa.array(list(data), pa.binary()))
        return pd.Series([v[a:b].tolist() for a, b in zip(o[:-1], o[1:], strict=True)])

    def pip(px: pd.Series, py: pd.Series, ring: pd.Series) -> pd.Series:
        return pd.Series([bool(geometry.covers(np.array([[x, y]], np.int64), _points(r))[0]) for x, y, r in zip(px, py, ring, strict=True)])

    def pairwise(test):
        def run(a: pd.Series, b: pd.Series) -> pd.Series:
            return pd.Series([bool(test(_points(x), _points(y))) for x, y in zip(a, b, strict=True)])

        return run

    def runs_of(hid: pd.Series) -> list:
        ids = np.unique(hid.to_numpy(np.int64))
        return rasterize.runs(np.zeros(len(ids), np.int64), ids, 1)[0].tolist()

    for name, kind, f in (
        ("hilbert_id", "long", hilbert_id),
        ("hilbert_cell", "cx long, cy long", hilbert_cell),
        ("runs_overlap", "boolean", runs_overlap),
        ("dual_verdict", "string", dual_verdict),
        ("dual_within_verdict", "string", dual_within_verdict),
        ("coded_verdict", "string", coded_verdict),
        ("aligned_and", "boolean", aligned_and),
        ("vbyte_encode", "binary", vbyte_encode),
        ("vbyte_decode", "array<bigint>", vbyte_decode),
        ("pip", "boolean", pip),
        ("polygons_intersect", "boolean", pairwise(geometry.polygons_intersect)),
        ("polygon_within", "boolean", pairwise(geometry.polygon_within)),
        ("line_intersects", "boolean", pairwise(geometry.line_intersects)),
    ):
        f.__annotations__ = {k: pd.DataFrame if v in (pd.DataFrame, "pd.DataFrame") else pd.Series for k, v in f.__annotations__.items()}
        _scalar(spark, name, kind, f)
    spark.udf.register("runs_of", F.pandas_udf(runs_of, "array<bigint>", F.PandasUDFType.GROUPED_AGG))

    class EdgeCells:
        def eval(self, ring, order: int) -> Iterator[tuple]:
            pts = _points(ring)
            _, h = rasterize.edge_ids(rasterize.Batch(pts, np.array([0, len(pts)]), GridSpec(order)))
            x, y = hilbert.decode(h, order)
            yield from zip(x.tolist(), y.tolist(), h.tolist(), strict=True)

    class DualRuns:
        def eval(self, ring, order: int) -> Iterator[tuple]:
            pts = _points(ring)
            got = rasterize.onestep(rasterize.Batch(pts, np.array([0, len(pts)]), GridSpec(order)))
            for name in ("cover", "core"):
                v = got[name][0].tolist()
                for a, b in zip(v[0::2], v[1::2], strict=True):
                    yield name, a, b

    spark.udtf.register("edge_cells", F.udtf(EdgeCells, returnType="cx bigint, cy bigint, hid bigint"))
    spark.udtf.register("dual_runs", F.udtf(DualRuns, returnType="list string, st bigint, en bigint"))
