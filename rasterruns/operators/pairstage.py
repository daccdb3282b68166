"""One Arrow stage over pairs in which the larger side's data travel once, not once a pair.

Pairs carry the smaller side's columns; the other side's rows join the same
partitions and stand just before their pairs.  A kernel gets the pairs of a
batch and a table of the distinct large rows with an index from pair to row.
An object with more than SPLIT pairs is dealt over several parts, each with a
copy of its row, so no key is bound to one task.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.runtime import materialize

SPLIT = 4096
#: Rows up to which the table of objects with more than SPLIT pairs is broadcast.
BROADCAST_ROWS = 1_000_000


def pair_stage(pairs: DataFrame, small: DataFrame, large: DataFrame, small_id: str, large_id: str, kernel: Callable, schema: str) -> DataFrame:
    """``pairs`` hold both ids (and perhaps tile_id); ``small``/``large`` are keyed by oid (and tile_id).

    ``kernel(pairs, large, at)``: record batches of the pairs with the small
    side's columns and of large rows, and the large row of each pair; returns a
    record batch.
    """
    if not hasattr(pairs, "_cut_path"):
        # ids are cut once: they are read for the counts and for the deal, and whatever found them runs once
        tile = F.col("tile_id") if "tile_id" in pairs.columns else F.lit(0)
        pairs = materialize(pairs.select(tile.cast("int").alias("tile_id"), "rid", "sid"))
    elif "tile_id" not in pairs.columns:
        pairs = pairs.withColumn("tile_id", F.lit(0))
    keys = ["tile_id", large_id]

    def side(df: DataFrame, name: str, prefix: str) -> DataFrame:
        tile = F.col("tile_id").cast("int") if "tile_id" in df.columns else F.lit(0)
        return df.select(tile.alias("tile_id"), F.col("oid").alias(name), *[F.col(c).alias(f"{prefix}{c}") for c in df.columns if c not in ("oid", "tile_id")])

    rows = side(small, small_id, "p_")
    big = side(large, large_id, "q_")
    on_small = ["tile_id", small_id] if "tile_id" in small.columns else [small_id]
    rows = rows if "tile_id" in small.columns else rows.drop("tile_id")
    on_large = ["tile_id", large_id] if "tile_id" in large.columns else [large_id]
    parts = materialize(pairs.groupBy(*keys).agg(F.ceil(F.count(F.lit(1)) / SPLIT).cast("int").alias("parts")))
    hot = parts.where("parts > 1")
    if hot.count() <= BROADCAST_ROWS:
        hot = F.broadcast(hot)  # so hot objects are dealt before anything is keyed by them
    part = F.pmod(F.xxhash64(small_id), F.coalesce("parts", F.lit(1))).cast("int")
    dealt = pairs.select("tile_id", "rid", "sid").join(hot, keys, "left").withColumn("part", part).drop("parts")
    dealt = dealt.join(rows, on_small)
    copies = parts.join(big if "tile_id" in large.columns else big.drop("tile_id"), on_large).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    one = dealt.withColumn("kind", F.lit(1))
    two = copies.withColumn("kind", F.lit(0))
    both = one.unionByName(two, allowMissingColumns=True)
    order = ["tile_id", large_id, "part", "kind"]
    both = both.repartition(*order[:3]).sortWithinPartitions(*order)
    p_columns = ["tile_id", "rid", "sid", *[c for c in rows.columns if c.startswith("p_")]]
    q_columns = [c for c in big.columns if c.startswith("q_")]
    both = both.select("kind", *p_columns, *q_columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        carried: pa.Table | None = None
        for batch in batches:
            kind = batch.column(0).to_numpy()
            heads, here = np.flatnonzero(kind == 0), np.flatnonzero(kind == 1)
            names = ["tile_id", large_id, *q_columns]
            large_rows = pa.table([batch.column(c).take(pa.array(heads)) for c in names], names=names)
            if carried is not None:
                large_rows = pa.concat_tables([carried, large_rows])
            at = np.searchsorted(heads, here) - 1 + (carried is not None)
            if len(here) and large_rows.num_rows:
                # a pair without its large row has another object's before it, or none
                known = at >= 0
                for c in ("tile_id", large_id):
                    known &= batch.column(c).to_numpy()[here] == large_rows.column(c).to_numpy()[at]
                here, at = here[known], at[known]
                own = pa.RecordBatch.from_arrays([batch.column(c).take(pa.array(here)) for c in p_columns], names=p_columns)
                if len(here):
                    yield kernel(own, large_rows.combine_chunks().to_batches()[0], at)
            if large_rows.num_rows:
                carried = large_rows.slice(large_rows.num_rows - 1)

    return both.mapInArrow(run, schema)
