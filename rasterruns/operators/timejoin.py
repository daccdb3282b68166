"""As-of join: each left row with the last right row of its key not after it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, columns: list[str]) -> DataFrame:
    """Union both sides, then carry the last right-hand values forward in one window: one shuffle, no range join.

    Right rows with an equal time count; nulls in ``columns`` are carried as values.
    """
    marked = right.select(F.col(key), F.col(at), F.lit(0).alias("_side"), F.struct(*columns).alias("_right"))
    own = [c for c in left.columns if c not in (key, at)]
    rows = left.select(F.col(key), F.col(at), F.lit(1).alias("_side"), F.struct(*own).alias("_left"))
    both = rows.unionByName(marked, allowMissingColumns=True)
    line = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = both.withColumn("_last", F.last("_right", ignorenulls=True).over(line)).where("_side = 1")
    return both.select(key, at, *[F.col(f"_left.{c}").alias(c) for c in own], *[F.col(f"_last.{c}").alias(c) for c in columns])
