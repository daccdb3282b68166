"""The store of approximations: Parquet by layer, order and tile, sorted so that scans skip."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_dual(dual: DataFrame, path: str, layer: str, mode: str = "append") -> None:
    """Write dual runs; a file holds a stretch of tiles and, within, of first ids.

    Appending new objects leaves the files of others alone.
    """
    rows = dual.withColumn("layer", F.lit(layer)).withColumn("first_id", F.get("cover", F.lit(0)) if dict(dual.dtypes)["cover"] != "binary" else F.lit(None).cast("long"))
    rows.repartitionByRange("tile_id", "oid").sortWithinPartitions("tile_id", "first_id").write.mode(mode).partitionBy("layer", "ord").parquet(path)


def read_dual(spark: SparkSession, path: str, layer: str, order: int) -> DataFrame:
    """Dual runs of a layer at an order: partition folders prune both."""
    return spark.read.parquet(path).where((F.col("layer") == layer) & (F.col("ord") == order)).drop("layer", "first_id")


def write_layer(layer: DataFrame, path: str) -> None:
    """Geometry sorted by box corner, so that row groups cover small windows and predicates skip them."""
    layer.repartitionByRange("xmin", "ymin").sortWithinPartitions("xmin", "ymin").write.mode("overwrite").parquet(path)


def read_layer(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


_SCHEMA = "oid bigint, grp bigint, ring array<struct<x:bigint,y:bigint>>, xmin bigint, ymin bigint, xmax bigint, ymax bigint, n_vertices int"


def read_json_layer(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(_SCHEMA).json(path)


def read_orc_layer(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(_SCHEMA).orc(path)


def read_csv_layer(spark: SparkSession, path: str, closed: bool = True) -> DataFrame:
    """Lines of id and well-known text."""
    from rasterruns.sources.layers import with_mbr
    from rasterruns.sources.wkt import from_wkt

    rows = spark.read.schema("oid bigint, wkt string").option("sep", "\t").csv(path)
    column = "ring" if closed else "path"
    return with_mbr(rows.select("oid", F.lit(None).cast("long").alias("grp"), from_wkt(F.col("wkt")).alias(column)), column)
