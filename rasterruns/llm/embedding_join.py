"""Embedding near-duplicates by an epsilon grid order join.

Unit vectors with cosine >= t lie within eps = sqrt(2 - 2 t) of each other, and
no rotation changes that.  The vectors are rotated to principal dimensions (the
rotation is fitted on a bounded sample; any rotation gives the same results)
and sorted by their grid cells of side eps on the leading ones.  The sorted
sequence is cut into blocks with bounding boxes.  Pairs of sequence intervals
are joined recursively: an interval pair whose boxes are further apart than eps
is skipped, a small one is compared in double precision, others are halved.

Blocks form strips, and a task joins two strips, so a block is sent to as many
tasks as there are strips in reach rather than to one for each partner block.
Equal vectors are one vector with a weight.  A task returns counts and a
spanning forest of its links, at most two rows a vector however dense the links
are.

Defined results: null, zero and non-finite vectors (and vectors with null
components) link with nothing and stay as rows of their own; vectors of
different lengths never link; a row without an id gets a row with null
component; rows that share an id are judged by their own vectors, each as a
vector of its own; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.llm.common import materialize
from rasterruns.llm.components import connected_components
from rasterruns.llm.vectors import matrices

#: Rows for fitting the rotation, leading dimensions, rows in a block, blocks in a strip, rows compared at once.
FIT_ROWS = 10_000
LEADING = 8
BLOCK = 1024
STRIP = 16
LEAF = 256
#: Allowance for rounding when boxes are compared.
SLACK = 1e-6


def _valid(df: DataFrame, key: str, vector: str) -> DataFrame:
    """``(vec_id, d, v)`` of every row; d and v are null where the row takes no part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, at = batch.column(0), pa.array(np.arange(batch.num_rows))
            rest = np.ones(batch.num_rows, bool)
            for d, row, m in matrices(at, batch.column(1)):
                fine = (np.abs(m).max(axis=1) > 0 if d else np.zeros(len(m), bool)) & ids.take(pa.array(row)).is_valid().to_numpy(zero_copy_only=False)
                row, m = row[fine], m[fine] + 0.0  # no negative zero
                rest[row] = False
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(row)), pa.array(np.full(len(m), d), pa.int32()), pa.array([r.tobytes() for r in m], pa.binary())], names=["vec_id", "d", "v"])
            n = int(rest.sum())
            yield pa.RecordBatch.from_arrays([ids.filter(pa.array(rest)), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())], names=["vec_id", "d", "v"])

    return df.select(df[key].cast("long").alias("vec_id"), df[vector].alias("v")).mapInArrow(run, "vec_id long, d int, v binary")


def _unit(packed: list[bytes], d: int) -> np.ndarray:
    m = np.frombuffer(b"".join(packed)).reshape(-1, d)
    m = m / np.abs(m).max(axis=1, keepdims=True)
    return m / np.sqrt(np.einsum("ij,ij->i", m, m))[:, None]


def _rotation(rows: DataFrame, d: int, total: int) -> np.ndarray:
    """Leading principal directions of at most FIT_ROWS vectors, chosen by a hash of the id."""
    share = min(1.0, FIT_ROWS / max(total, 1))
    sample = rows.where(F.pmod(F.xxhash64("rep"), F.lit(1 << 20)) <= int(share * (1 << 20))).select("v").limit(FIT_ROWS).toPandas()["v"].tolist()
    u = _unit([bytes(x) for x in sample], d) if sample else np.eye(d)
    u = u - u.mean(axis=0)
    _, axes = np.linalg.eigh(u.T @ u)  # ascending
    return axes[:, ::-1][:, : min(LEADING, d)].copy()


def _sequence(rows: DataFrame, d: int, axes: np.ndarray, eps: float) -> DataFrame:
    """``rows(rep, n, v)`` -> the same with grid cells ``c`` on the leading dimensions, sorted into partitions by them."""
    m = axes.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells = np.floor((_unit(batch.column(2).to_pylist(), d) @ axes) / eps).astype(np.int32) if batch.num_rows else np.zeros((0, m), np.int32)
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(cells[:, j]) for j in range(m))], names=["rep", "n", "v", *(f"c{j}" for j in range(m))])

    out = rows.select("rep", "n", "v").mapInArrow(run, "rep long, n long, v binary, " + ", ".join(f"c{j} int" for j in range(m)))
    order = [*(f"c{j}" for j in range(m)), "rep"]
    return out.repartitionByRange(*order).sortWithinPartitions(*order).select("rep", "n", "v")


def _blocks(ordered: DataFrame, d: int, axes: np.ndarray) -> DataFrame:
    """Blocks of at most BLOCK vectors in sequence, with the box of their leading coordinates."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, weights, rows = [], [], []

        def block():
            y = _unit(rows, d) @ axes
            return pa.RecordBatch.from_arrays([pa.array([np.array(ids, np.int64).tobytes()], pa.binary()), pa.array([np.array(weights, np.int64).tobytes()], pa.binary()), pa.array([b"".join(rows)], pa.binary()), pa.array([y.min(0).tolist()], pa.list_(pa.float64())), pa.array([y.max(0).tolist()], pa.list_(pa.float64()))], names=["ids", "weights", "rows", "low", "high"])

        for batch in batches:
            for i, w, v in zip(*(batch.column(j).to_pylist() for j in range(3)), strict=True):
                ids.append(i)
                weights.append(w)
                rows.append(v)
                if len(ids) == BLOCK:
                    yield block()
                    ids, weights, rows = [], [], []
        if ids:
            yield block()

    return ordered.mapInArrow(run, "ids binary, weights binary, rows binary, low array<double>, high array<double>").withColumn("block", F.monotonically_increasing_id())


def _forest(mask: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spanning edges of the links in ``mask`` between ids ``a`` and ``b``: smallest labels spread until they rest."""
    r, c = mask.any(axis=1), mask.any(axis=0)
    mask, a, b = mask[np.ix_(r, c)], a[r], b[c]
    big = np.iinfo(np.int64).max
    la, lb = a.copy(), b.copy()
    while True:
        na = np.minimum(la, np.where(mask, lb[None, :], big).min(axis=1))
        nb = np.minimum(lb, np.where(mask, na[:, None], big).min(axis=0))
        if (na == la).all() and (nb == lb).all():
            return np.concatenate([a, b]), np.concatenate([la, lb])
        la, lb = na, nb


class _Strip:
    """A strip's vectors in sequence, with unit rows and leading coordinates."""

    def __init__(self, parts: list[tuple], d: int, axes: np.ndarray):
        parts = sorted(parts, key=lambda p: p[0])
        self.ids = np.concatenate([np.frombuffer(p[1], np.int64) for p in parts])
        self.weights = np.concatenate([np.frombuffer(p[2], np.int64) for p in parts])
        self.u = _unit([p[3] for p in parts], d)
        self.y = self.u @ axes


def _join(a: _Strip, b: _Strip, same: bool, least: float, eps: float):
    """Links between two strips (each pair once): partial counts for both sides and forest edges."""
    na, nb = np.zeros(len(a.ids), np.int64), np.zeros(len(b.ids), np.int64)
    edges = []
    todo = [(0, len(a.ids), 0, len(b.ids))]
    while todo:
        i, j, k, m = todo.pop()
        if i >= j or k >= m or (same and k >= j):
            continue
        gap = np.maximum(0, np.maximum(a.y[i:j].min(0) - b.y[k:m].max(0), b.y[k:m].min(0) - a.y[i:j].max(0)))
        if gap @ gap > (eps + SLACK) ** 2:
            continue
        if j - i <= LEAF and m - k <= LEAF:
            mask = a.u[i:j] @ b.u[k:m].T >= least
            if same:
                mask &= np.arange(i, j)[:, None] > np.arange(k, m)[None, :]
            if mask.any():
                na[i:j] += mask @ b.weights[k:m]
                nb[k:m] += a.weights[i:j] @ mask
                edges.append(_forest(mask, a.ids[i:j], b.ids[k:m]))
            continue
        halves_a = [(i, j)] if j - i <= LEAF else [(i, (i + j) // 2), ((i + j) // 2, j)]
        halves_b = [(k, m)] if m - k <= LEAF else [(k, (k + m) // 2), ((k + m) // 2, m)]
        todo += [(*p, *q) for p in halves_a for q in halves_b]
    return na, nb, edges


def _strip_pairs(blocks: DataFrame, m: int, eps: float) -> DataFrame:
    """Pairs of strips whose boxes come within eps on all leading dimensions.

    An equi-join on the reachable cells of the first dimension, then the distance of the boxes.
    """
    lows = [F.min(F.element_at("low", j + 1)).alias(f"lo{j}") for j in range(m)]
    highs = [F.max(F.element_at("high", j + 1)).alias(f"hi{j}") for j in range(m)]
    boxes = blocks.groupBy("strip").agg(*lows, *highs)
    cell = lambda c: F.floor(F.col(c) / eps)
    corners = lambda p: [F.col(f"{x}{j}").alias(f"{p}{x}{j}") for x in ("lo", "hi") for j in range(m)]
    left = boxes.select(F.col("strip").alias("s"), *corners("s"), F.explode(F.sequence(cell("lo0") - 1, cell("hi0") + 1)).alias("cell"))
    right = boxes.select(F.col("strip").alias("t"), *corners("t"), F.explode(F.sequence(cell("lo0"), cell("hi0"))).alias("cell"))
    gap = F.lit(0.0)
    for j in range(m):
        apart = F.greatest(F.lit(0.0), F.col(f"tlo{j}") - F.col(f"shi{j}"), F.col(f"slo{j}") - F.col(f"thi{j}"))
        gap = gap + apart * apart
    return left.join(right, "cell").where((F.col("s") >= F.col("t")) & (gap <= (eps + SLACK) ** 2)).select("s", "t").distinct()


def _links(rows: DataFrame, d: int, total: int, least: float) -> DataFrame:
    """``(vec, other, n)``: partial link counts (other null) and forest edges (n null)."""
    eps = float(np.sqrt(max(0.0, 2 - 2 * least)))
    axes = _rotation(rows, d, total)
    blocks = materialize(_blocks(_sequence(rows, d, axes, eps), d, axes))
    count = blocks.count()
    size = max(1, min(STRIP, count // 8))
    # a block's number holds its partition in the upper bits; strips are stretches within a partition
    part = F.shiftright("block", 33)
    places = blocks.select("block", "low", "high").withColumn("strip", F.shiftleft(part, 33) + F.floor((F.col("block") - F.shiftleft(part, 33)) / size))
    pairs = _strip_pairs(places, axes.shape[1], eps)
    where = places.select("block", "strip")
    data = blocks.select("block", "ids", "weights", "rows").join(where, "block")
    sides = pairs.withColumn("side", F.explode(F.when(F.col("s") == F.col("t"), F.array(F.lit(0))).otherwise(F.array(F.lit(0), F.lit(1))))).withColumn("strip", F.when(F.col("side") == 0, F.col("s")).otherwise(F.col("t")))
    sent = data.join(sides, "strip")
    out = pa.schema([("vec", pa.int64()), ("other", pa.int64()), ("n", pa.int64())])

    def run(key, table):
        parts = {0: [], 1: []}
        for r in table.to_pylist():
            parts[r["side"]].append((r["block"], r["ids"], r["weights"], r["rows"]))
        a = _Strip(parts[0], d, axes)
        same = not parts[1]
        b = a if same else _Strip(parts[1], d, axes)
        na, nb, edges = _join(a, b, same, least, eps)
        ids = np.concatenate([a.ids[na > 0], b.ids[nb > 0]])
        n = np.concatenate([na[na > 0], nb[nb > 0]])
        u, v = (np.concatenate(x) for x in zip(*edges, strict=True)) if edges else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        keep = np.unique(np.stack([u, v], 1)[u != v], axis=0) if len(u) else np.zeros((0, 2), np.int64)
        return pa.table([pa.array(np.concatenate([ids, keep[:, 0]])), pa.array([None] * len(ids) + keep[:, 1].tolist(), pa.int64()), pa.array(n.tolist() + [None] * len(keep), pa.int64())], schema=out)

    return sent.groupBy("s", "t").applyInArrow(run, "vec long, other long, n long")


def near_duplicates(df: DataFrame, least: float = 0.9, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """One row per row of ``df``: vec_id, n_links, component_id (smallest id reachable), kept."""
    spark = df.sparkSession
    rows = materialize(_valid(df, key, vector))
    # one number for each different vector, fixed by the files
    reps = rows.where("v IS NOT NULL").groupBy("d", "v").agg(F.min("vec_id").alias("least_id"), F.count(F.lit(1)).alias("n"))
    reps = materialize(reps.withColumn("rep", F.monotonically_increasing_id()))
    found = spark.createDataFrame([], "vec long, other long, n long")
    for d, total in reps.groupBy("d").count().orderBy("d").collect():
        found = found.union(_links(reps.where(F.col("d") == d).select("rep", "n", "v"), d, total, least))
    found = materialize(found)
    counts = found.where("n is not null").groupBy(F.col("vec").alias("rep")).agg(F.sum("n").alias("linked"))
    component = connected_components(found.where("other is not null").select(F.col("vec").alias("u"), F.col("other").alias("v")))
    known = reps.join(counts, "rep", "left").join(component, F.col("rep") == F.col("node"), "left").withColumn("component", F.coalesce("component", "rep"))
    smallest = known.groupBy("component").agg(F.min("least_id").alias("component_id"))
    known = known.join(smallest, "component").select("d", "v", (F.coalesce("linked", F.lit(0)) + F.col("n") - 1).alias("n_links"), "component_id")
    out = rows.join(known, ["d", "v"], "left").select(F.col("vec_id").alias(key), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col(key) == F.col("component_id"))
