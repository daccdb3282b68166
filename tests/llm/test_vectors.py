"""Embedding near-duplicates and exact search against brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rasterruns.llm import embedding_join, queries, vector_file


def odd_vectors(spark):
    rnd = np.random.default_rng(5)
    base = rnd.normal(size=8)
    rows = [(i, [float(x) for x in base + rnd.normal(scale=0.2, size=8)], "x") for i in range(40)]
    rows += [(100 + i, [float(x) for x in base], "same") for i in range(30)]
    rows += [(200, None, "x"), (201, [0.0] * 8, "x"), (202, [float("nan")] + [1.0] * 7, "x"), (203, [float("inf")] + [1.0] * 7, None), (204, [None] + [1.0] * 7, "x"), (205, [1.0, 2.0], "short"), (206, [2.0, 4.0], "short"), (207, [], "none"), (250, [1e30] * 8, "large"), (300, [-0.0, 0.0, 1.0] + [0.0] * 5, "z"), (301, [0.0, -0.0, 1.0] + [0.0] * 5, "z")]
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, vec string")


def whole(rows):
    by = {}
    for i, v in rows:
        if v is not None and all(x is not None and np.isfinite(x) for x in v):
            by.setdefault(len(v), []).append((i, np.array(v, np.float64)))
    return by


def brute_links(rows, least):
    links = {i: set() for i, _ in rows}
    for d, group in whole(rows).items():
        group = [(i, v) for i, v in group if d and np.abs(v).max() > 0]
        for i, v in group:
            for j, w in group:
                if i != j and (v / np.abs(v).max()) @ (w / np.abs(w).max()) / np.linalg.norm(v / np.abs(v).max()) / np.linalg.norm(w / np.abs(w).max()) >= least:
                    links[i].add(j)
    root = {}
    for i in sorted(links):
        todo = [i]
        while todo:
            if (x := todo.pop()) not in root:
                root[x] = i
                todo += links[x]
    return {i: (len(links[i]), root[i], root[i] == i) for i in links}


@pytest.mark.parametrize("block,strip", [(1024, 16), (8, 2)])
def test_near_duplicates_equal_brute_force(spark, sf_dir, monkeypatch, block, strip):
    monkeypatch.setattr(embedding_join, "BLOCK", block)
    monkeypatch.setattr(embedding_join, "STRIP", strip)
    monkeypatch.setattr(embedding_join, "LEAF", 4 if block == 8 else 256)
    df = odd_vectors(spark)
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_join.near_duplicates(df).collect()}
    assert got == brute_links([(r.vec_id, r.embedding) for r in df.collect()], 0.9)
    assert embedding_join.near_duplicates(df.limit(0)).count() == 0


def test_rows_that_share_an_id(spark):
    df = spark.createDataFrame([(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 0.01]), (None, [1.0, 0.0]), (3, [0.0, 0.0])], "vec_id long, embedding array<float>")
    got = sorted(map(tuple, embedding_join.near_duplicates(df).collect()), key=str)
    assert got == sorted([(1, 1, 1, True), (1, 0, 1, True), (2, 1, 1, False), (None, 0, None, None), (3, 0, 3, True)], key=str)


def test_strips_are_compared_on_all_dimensions(spark):
    boxes = [(0, [0.0, 0.0], [0.1, 0.1]), (1, [0.0, 5.0], [0.1, 5.1]), (2, [0.05, 0.3], [0.2, 0.4])]
    df = spark.createDataFrame(boxes, "strip long, low array<double>, high array<double>")
    got = {tuple(r) for r in embedding_join._strip_pairs(df, 2, 0.45).collect()}
    assert got == {(0, 0), (1, 1), (2, 2), (2, 0)}


def test_near_duplicates_of_the_table(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in queries.op3_embedding_dedup(spark, sf_dir).collect()}
    assert got == brute_links([(r.vec_id, r.embedding) for r in df.collect()], 0.9)


def brute_search(rows, queries_, k):
    out = []
    for group in whole(rows).values():
        q = {i: [int(np.floor(256 * x)) for x in v] for i, v in group}
        for i in q:
            if i in queries_:
                best = sorted((-max(min(sum(a * b for a, b in zip(q[i], q[j], strict=True)), 2**63 - 1), -(2**63)), j) for j in q if j != i)[:k]
                out += [(i, n, j, -s) for n, (s, j) in enumerate(best, 1)]
    return sorted(out)


def test_search_equals_brute_force(spark, sf_dir, monkeypatch):
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    rows = [(r.vec_id, r.embedding) for r in df.collect()]
    assert sorted(map(tuple, queries.op4_vector_search(spark, sf_dir).collect())) == brute_search(rows, {i for i, _ in rows if i % 50 == 0}, 5)
    monkeypatch.setattr(vector_file, "QUERY_BLOCK", 16)
    odd = odd_vectors(spark)
    rows = [(r.vec_id, r.embedding) for r in odd.collect()]
    got = vector_file.search(odd, F.col("vec_id") >= 0)
    assert sorted(map(tuple, got.collect())) == brute_search(rows, {i for i, _ in rows}, 5)
    assert vector_file.search(odd.limit(0), F.col("vec_id") >= 0).count() == 0


def test_search_reads_by_bounds_and_stops_early(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(vector_file, "FIRST_READ", 5)
    rnd = np.random.default_rng(2)
    rows = [(i, [float(x) for x in rnd.normal(size=24)]) for i in range(3000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    trace = []
    got = sorted(map(tuple, vector_file.search(df, F.col("vec_id") % 50 == 0, trace=trace).collect()))
    assert got == brute_search(rows, {i for i in range(0, 3000, 50)}, 5)
    survivors, reads = map(sum, zip(*((n, sum(r)) for n, r in trace), strict=True))
    assert len(trace[0][1]) > 1 and reads < survivors


def test_ties_at_the_last_rank_go_to_smaller_ids(spark, monkeypatch):
    monkeypatch.setattr(vector_file, "FIRST_READ", 5)
    rows = [(i, [1.0, float(i % 3 == 0)]) for i in range(60)] + [(7, [1.0, 1.0]), (100, [2.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [tuple(r) for r in vector_file.search(df, F.col("vec_id") == 100).orderBy("rank").collect()]
    assert got == [(100, n, i, 3 * 256 * 256) for n, i in enumerate([0, 3, 6, 7, 9], 1)]


def test_cells_take_six_bits():
    cells = np.random.default_rng(1).integers(0, 64, (7, 11)).astype(np.uint8)
    packed = vector_file._pack(cells)
    assert packed.shape == (7, 9)
    import pyarrow as pa

    assert (vector_file._unpack_cells(pa.array([r.tobytes() for r in packed], pa.binary()), 11) == cells).all()
