"""Exact tests on the pairs that a filter leaves unsure; geometry is fetched for those only."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.functions import pairtests
from rasterruns.operators.approximate import points
from rasterruns.operators.pairstage import pair_stage

#: predicate -> (test of a batch, column of the right side)
TESTS = {
    "intersects": (pairtests.intersects, "ring"),
    "within": (pairtests.within, "ring"),
    "line": (pairtests.line_meets, "path"),
}


def refine(pairs: DataFrame, left: DataFrame, right: DataFrame, predicate: str = "intersects", large: str | None = None) -> DataFrame:
    """``(rid, sid)`` of the pairs for which the predicate holds.

    ``large`` names the side of an intersection with the longer rings, sent once
    for all their pairs (by default the right one; the container, and the
    polygons of a line join, always are).
    """
    test, column = TESTS[predicate]
    r = left.select("oid", F.col("ring").alias("points"))
    s = right.select("oid", F.col(column).alias("points"))
    left_large = predicate == "line" or (predicate == "intersects" and large == "left")

    def kernel(own: pa.RecordBatch, table: pa.RecordBatch, at: np.ndarray) -> pa.RecordBatch:
        small = pairtests.Shapes(*points(own.column("p_points")), closed=predicate != "line")
        large = pairtests.Shapes(*points(table.column("q_points")))
        keep = pa.array(test(small, large, at))
        return pa.RecordBatch.from_arrays([own.column("rid").filter(keep), own.column("sid").filter(keep)], names=["rid", "sid"])

    sides = (s, r, "sid", "rid") if left_large else (r, s, "rid", "sid")
    return pair_stage(pairs.select("rid", "sid"), *sides, kernel, "rid long, sid long")
