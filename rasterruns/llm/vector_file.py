"""Exact top-k search with a vector-approximation file.

Vectors are integer components ``floor(scale * x)``; the score is the integer
inner product.  The approximation file holds 6 bits a component: the cell of
the component on a per-dimension grid between its least and greatest value.
A scan of the cells alone bounds every score from both sides.  A vector stays
a candidate while its upper bound reaches the k-th best lower bound.  Exact
vectors of the candidates are read best bound first, in rounds of growing
size; a query stops when its k-th exact score exceeds the next upper bound.

Queries come in blocks of at most QUERY_BLOCK rows: a block is broadcast, so
the broadcast's size is fixed, and each block scans all cells once.  Copies of
one vector score alike, and ties go to the smaller id, so of equal vectors only
the k + 1 with the smallest ids can be results (one may be the query itself);
the others are left out of the file.

Defined results: vectors that are null or hold a null or non-finite component
take no part, nor do rows without an id; only vectors of equal length are
compared; a row is its query's own if it has the query's id; repeated rows of a
query answer once, repeated candidates by (score, id); scores beyond 64 bits
are held at the limits; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rasterruns.llm.common import materialize, release
from rasterruns.llm.vectors import matrices

#: Cells a dimension (BITS bits each), queries in a block, and rows bounded at a time.
CELLS = 64
QUERY_BLOCK = 8192
BITS = 6
#: Candidates that a query reads in the first round; each round doubles what has been read.
FIRST_READ = 16
_ROWS = 2048
_LARGE = 1 << 26


def _exact(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row-wise integer inner products, held within 64 bits."""
    if not a.size:
        return np.zeros(len(a), np.int64)
    if max(np.abs(a).max(), np.abs(b).max()) < _LARGE:
        return np.einsum("ij,ij->i", a.astype(np.int64), b.astype(np.int64))
    whole = [sum(int(x) * int(y) for x, y in zip(p, q, strict=True)) for p, q in zip(a, b, strict=True)]
    return np.array([min(max(x, -(1 << 63)), (1 << 63) - 1) for x in whole], np.int64)


def quantised(df: DataFrame, key: str, vector: str, scale: int) -> DataFrame:
    """``(vec_id, d, q)``: integer components as packed doubles (exact for every float input)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, ids, m in matrices(batch.column(0), batch.column(1)):
                with np.errstate(over="ignore"):
                    q = np.floor(scale * m)
                fine = np.isfinite(q).all(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(ids[fine], pa.int64()), pa.array(np.full(fine.sum(), d), pa.int32()), pa.array([r.tobytes() for r in q[fine]], pa.binary())], names=["vec_id", "d", "q"])

    return df.select(df[key].cast("long").alias("vec_id"), df[vector].alias("v")).mapInArrow(run, "vec_id long, d int, q binary")


def _unpack(column: pa.Array, d: int, kind=np.float64) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), kind).reshape(len(column), d)


def _grid(pool: DataFrame, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Least component and cell width per dimension: d rows reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low = high = None
        for batch in batches:
            if batch.num_rows:
                m = _unpack(batch.column(0), d)
                low = m.min(0) if low is None else np.minimum(low, m.min(0))
                high = m.max(0) if high is None else np.maximum(high, m.max(0))
        if low is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(d), pa.int32()), pa.array(low), pa.array(high)], names=["j", "low", "high"])

    rows = pool.select("q").mapInArrow(run, "j int, low double, high double").groupBy("j").agg(F.min("low"), F.max("high")).orderBy("j").collect()
    low, high = np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
    return low, np.ceil((high - low + 1) / CELLS)


def _pack(cells: np.ndarray) -> np.ndarray:
    """Rows of cell numbers as rows of bytes, BITS bits a cell."""
    bits = np.unpackbits(cells[:, :, None], axis=2)[:, :, 8 - BITS :]
    return np.packbits(bits.reshape(len(cells), -1), axis=1)


def _unpack_cells(column: pa.Array, d: int) -> np.ndarray:
    packed = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), (d * BITS + 7) // 8)
    bits = np.unpackbits(packed, axis=1)[:, : d * BITS].reshape(len(column), d, BITS)
    return (bits @ (1 << np.arange(BITS)[::-1])).astype(np.float64)


def _cells(pool: DataFrame, d: int, low: np.ndarray, width: np.ndarray) -> DataFrame:
    """The approximation file ``(vec_id, cells)``, BITS bits a component."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells = np.clip((_unpack(batch.column(1), d) - low) // width, 0, CELLS - 1).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([c.tobytes() for c in _pack(cells)], pa.binary())], names=["vec_id", "cells"])

    return pool.select("vec_id", "q").mapInArrow(run, "vec_id long, cells binary")


def _scan(cells: DataFrame, d: int, low: np.ndarray, width: np.ndarray, block, k: int) -> DataFrame:
    """Candidates ``(query_id, vec_id, lower, upper)``: in each task, those that its own k-th lower bound leaves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = block.value
        slack = np.abs(q) @ ((width - 1) / 2)
        slack = slack + 1e-9 * (1 + np.abs(q) @ (np.abs(low) + CELLS * width))
        floor = np.full(len(qid), -np.inf)
        for batch in batches:
            ids = batch.column(0).to_numpy()
            middle = low + width * _unpack_cells(batch.column(1), d) + (width - 1) / 2
            for a in range(0, len(ids), _ROWS):
                part, some = ids[a : a + _ROWS], middle[a : a + _ROWS]
                for b in range(0, len(qid), _ROWS):
                    s = slice(b, b + _ROWS)
                    score = q[s] @ some.T
                    own = qid[s][:, None] == part[None, :]
                    score[own] = -np.inf
                    if score.shape[1] >= k:
                        kth = np.partition(score, score.shape[1] - k, axis=1)[:, -k]
                        floor[s] = np.maximum(floor[s], kth - slack[s])
                    i, j = np.nonzero((score + slack[s][:, None] >= floor[s][:, None]) & ~own)
                    value = score[i, j]
                    yield pa.RecordBatch.from_arrays([pa.array(qid[s][i]), pa.array(part[j]), pa.array(value - slack[s][i]), pa.array(value + slack[s][i])], names=["query_id", "vec_id", "lower", "upper"])

    return cells.mapInArrow(run, "query_id long, vec_id long, lower double, upper double")


def _refine(near: DataFrame, d: int, block) -> DataFrame:
    """Exact scores of ``near(query_id, vec_id, q)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = block.value
        order = np.argsort(qid)
        for batch in batches:
            at = order[np.searchsorted(qid[order], batch.column(0).to_numpy())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(_exact(q[at], _unpack(batch.column(2), d)))], names=["query_id", "vec_id", "score"])

    return near.mapInArrow(run, "query_id long, vec_id long, score long")


def _blocks(queries: DataFrame, d: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The queries in blocks of at most QUERY_BLOCK, one block on the driver at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, QUERY_BLOCK // 8):
                part = batch.slice(a, QUERY_BLOCK // 8)
                yield pa.RecordBatch.from_arrays([pa.array([part.column(0).to_numpy().tobytes()], pa.binary()), pa.array([b"".join(part.column(1).to_pylist())], pa.binary())], names=["ids", "q"])

    ids, rows = [], []
    for r in queries.select("vec_id", "q").mapInArrow(run, "ids binary, q binary").toLocalIterator():
        got = np.frombuffer(r.ids, np.int64)
        if sum(map(len, ids)) + len(got) > QUERY_BLOCK:
            yield np.concatenate(ids), np.concatenate(rows)
            ids, rows = [], []
        ids.append(got)
        rows.append(np.frombuffer(r.q).reshape(len(got), d))
    if ids:
        yield np.concatenate(ids), np.concatenate(rows)


def _read_in_order(near: DataFrame, vectors: DataFrame, d: int, block, k: int, trace: list | None) -> DataFrame:
    """The k best by exact score of ``near(query_id, vec_id, lower, upper)``, reading vectors best bound first.

    After each round a query is open while its next candidate's upper bound
    reaches its k-th exact score (equal scores may still win by the smaller id).
    """
    by_bound = Window.partitionBy("query_id").orderBy(F.col("upper").desc(), "vec_id")
    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    left = near.withColumn("place", F.row_number().over(by_bound))
    left = materialize(left.withColumn("after", F.lead("upper").over(by_bound)))
    done, top, open_ = 0, None, None
    while True:
        upto = 2 * done or max(FIRST_READ, k)
        turn = left.where((F.col("place") > done) & (F.col("place") <= upto))
        if open_ is not None:
            turn = turn.join(open_, "query_id", "left_semi")
        scored = _refine(turn.join(vectors, "vec_id").select("query_id", "vec_id", "q"), d, block)
        both = scored if top is None else top.select("query_id", "vec_id", "score").unionByName(scored)
        old, top = top, materialize(both.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k))
        if trace is not None:
            trace.append(turn.count())
        if old is not None:
            release(old)
        kth = top.groupBy("query_id").agg(F.when(F.count(F.lit(1)) == k, F.min("score")).alias("kth"))
        last = turn.where((F.col("place") == upto) & F.col("after").isNotNull()).select("query_id", "after")
        more = materialize(last.join(kth, "query_id").where("kth IS NULL OR after >= kth").select("query_id"))
        if open_ is not None:
            release(open_)
        done, open_ = upto, more
        if more.isEmpty():
            release(left, more)
            return top.select("query_id", "rank", "vec_id", "score")


def search(df: DataFrame, is_query, k: int = 5, key: str = "vec_id", vector: str = "embedding", scale: int = 256, trace: list | None = None) -> DataFrame:
    """Each query's k best of all other rows: query_id, rank (from 1), vec_id, score.

    ``is_query``: a condition on the column ``vec_id``.  ``trace`` takes, for
    each block of queries, (candidates that the bounds leave, vectors read by round).
    """
    spark = df.sparkSession
    rows = materialize(quantised(df, key, vector, scale).distinct())
    copies = Window.partitionBy("d", "q").orderBy("vec_id")
    pool = materialize(rows.withColumn("_c", F.row_number().over(copies)).where(F.col("_c") <= k + 1).drop("_c"))
    out = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    for (d,) in rows.select("d").distinct().orderBy("d").collect():
        mine = pool.where(F.col("d") == d)
        low, width = _grid(mine, d)
        cells = materialize(_cells(mine, d, low, width))
        for found in _blocks(rows.where((F.col("d") == d) & is_query).dropDuplicates(["vec_id"]), d):
            block = spark.sparkContext.broadcast(found)
            near = materialize(_scan(cells, d, low, width, block, k))
            ranked = Window.partitionBy("query_id").orderBy(F.col("lower").desc())
            top = near.withColumn("_r", F.row_number().over(ranked)).where(F.col("_r") <= k)
            certain = top.groupBy("query_id").agg(F.when(F.count(F.lit(1)) == k, F.min("lower")).otherwise(F.lit(float("-inf"))).alias("kth"))
            near = materialize(near.join(certain, "query_id").where("upper >= kth").drop("kth").dropDuplicates(["query_id", "vec_id"]))
            reads: list | None = None if trace is None else []
            top = _read_in_order(near, mine.select("vec_id", "q"), d, block, k, reads)
            if trace is not None:
                trace.append((near.count(), reads))
            release(near)
            out = out.union(top)
    return out
