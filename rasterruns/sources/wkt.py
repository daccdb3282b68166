"""Well-known text of polygons and paths: expressions, and a reader for files of lines."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


def to_wkt(points: Column, closed: bool) -> Column:
    """POLYGON (with the first point repeated at the end) or LINESTRING."""
    text = F.transform(points, lambda p: F.concat_ws(" ", p["x"].cast("string"), p["y"].cast("string")))
    if closed:
        return F.concat(F.lit("POLYGON (("), F.array_join(F.concat(text, F.slice(text, 1, 1)), ", "), F.lit("))"))
    return F.concat(F.lit("LINESTRING ("), F.array_join(text, ", "), F.lit(")"))


_PAIR = r"-?\d{1,18}\s+-?\d{1,18}"
_LIST = rf"\(\s*{_PAIR}\s*(?:,\s*{_PAIR}\s*)*\)"
#: What is read exactly: a polygon of one closed ring, or a path, with integer coordinates.
_RING = rf"(?i)^\s*POLYGON\s*\(\s*{_LIST}\s*\)\s*$"
_PATH = rf"(?i)^\s*LINESTRING\s*{_LIST}\s*$"


def from_wkt(text: Column) -> Column:
    """Points of a one-ring polygon (without the repeated one) or of a path.

    Null for any other text: holes, several parts, decimals, a third
    coordinate, a ring that isn't closed.  ``wkt_rejects`` lists such rows.
    """
    pairs = F.regexp_extract_all(text, F.lit(rf"({_PAIR})"), F.lit(1))
    part = lambda p, i: F.regexp_extract(p, r"^(-?\d+)\s+(-?\d+)$", i).cast("long")
    points = F.transform(pairs, lambda p: F.struct(part(p, 1).alias("x"), part(p, 2).alias("y")))
    closed = (F.size(points) > 3) & (F.element_at(points, 1) == F.element_at(points, -1))
    return F.when(text.rlike(_RING), F.when(closed, F.slice(points, F.lit(1), F.size(points) - 1))).when(text.rlike(_PATH), points)


def wkt_rejects(rows: DataFrame, column: str = "wkt") -> DataFrame:
    """Rows whose text isn't read."""
    return rows.where(from_wkt(F.col(column)).isNull())


class _Part(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]

    def partitions(self):
        import glob
        import os

        files = sorted(glob.glob(os.path.join(self.path, "*.wkt"))) if os.path.isdir(self.path) else [self.path]
        return [_Part(f) for f in files]

    def read(self, partition: _Part) -> Iterator[tuple]:
        with open(partition.path) as lines:
            for line in lines:
                oid, _, text = line.rstrip("\n").partition("\t")
                if text:
                    yield int(oid), text


class _Message(WriterCommitMessage):
    pass


class _Writer(DataSourceWriter):
    def __init__(self, options: dict):
        self.path = options["path"]

    def write(self, rows: Iterator) -> WriterCommitMessage:
        import os
        import uuid

        os.makedirs(self.path, exist_ok=True)
        with open(os.path.join(self.path, f"part-{uuid.uuid4().hex}.wkt"), "w") as out:
            for r in rows:
                out.write(f"{r[0]}\t{r[1]}\n")
        return _Message()


class WktLines(DataSource):
    """``format("wktlines")``: folders of files with an id, a tab and a well-known text on each line.

    For folders that all executors mount; other stores go through
    ``spark.read.text`` and ``from_wkt``.
    """

    @classmethod
    def name(cls) -> str:
        return "wktlines"

    def schema(self) -> str:
        return "oid bigint, wkt string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(WktLines)
