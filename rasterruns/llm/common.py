"""Shared plumbing of the training-data operators: materialised cuts, seeds, scalable ranks."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rasterruns.runtime import materialize, release

__all__ = ["WORD_PATTERN", "materialize", "release", "salted_rank", "sliced", "table"]

#: Rows of an Arrow batch that are turned into Python objects at once.
SLICE_ROWS = 256

#: Fixed value: the characters that separate words in every word contract (space, tab to carriage return).
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sliced(batches: Iterator[pa.RecordBatch], rows: int = SLICE_ROWS) -> Iterator[pa.RecordBatch]:
    """Batches of texts in slices (views), so that few texts are Python objects at the same time."""
    for batch in batches:
        for a in range(0, batch.num_rows, rows):
            yield batch.slice(a, rows)


def salted_rank(df: DataFrame, group: list[str], order: list, bucket, name: str, few: bool = False) -> DataFrame:
    """Add ``name``: gapless rank from 0 within ``group``, without one task per group.

    ``bucket`` is a Column that splits each group into ordered parts; a part's
    rows are numbered in its own task and shifted by the counts of the parts
    before it.  The table of part counts holds one row per (group, part), so it
    is bounded by groups x parts whatever the number of rows.  ``few``: the
    groups are a fixed number, so that table is broadcast and the rows, wide or
    not, are shuffled once.
    """
    rows = df.withColumn("_part", bucket)
    keys = [*group, "_part"]
    sizes = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"))
    offsets = F.broadcast(offsets) if few else offsets
    numbered = rows.withColumn("_rn", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)) - 1)
    cond = [numbered[k].eqNullSafe(offsets[f"_k{i}"]) for i, k in enumerate(keys)]
    joined = numbered.join(offsets, cond, "inner")
    return joined.withColumn(name, (F.col("_rn") + F.col("_off")).cast("long")).drop("_part", "_rn", "_off", *[f"_k{i}" for i in range(len(keys))])
