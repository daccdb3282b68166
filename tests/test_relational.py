"""The range joins cover every row: compared with brute force on small tables."""

import random

import pytest

from rasterruns.queries import relational


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    r = random.Random(5)
    lines = [(o, n, r.randrange(1, 400), r.randrange(1, 60), float(r.randrange(1, 51))) for o in range(1, 301) if o % 5 for n in range(1, r.randrange(2, 8))]
    cells = list(range(1, 300, 3))
    d = str(tmp_path_factory.mktemp("tables"))
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double").write.parquet(f"{d}/lineitem.parquet")
    spark.createDataFrame([(c,) for c in cells], "s_suppkey long").write.parquet(f"{d}/supplier.parquet")
    return d, lines, cells


def rows(df):
    got = [tuple(x) for x in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


def test_range_cells_of_all_orders(spark, tables):
    d, lines, cells = tables
    parts = {}
    for o, _, p, _, _ in lines:
        parts.setdefault(o, []).append(p)
    assert rows(relational.Q["join_range_cells"](spark, d)) == {(o, c) for o, ps in parts.items() for c in cells if min(ps) <= c <= max(ps)}


def test_interval_runs_of_all_lines(spark, tables):
    d, lines, _ = tables
    runs = [(s, o, o + n) for o, n, _, s, _ in lines]
    assert rows(relational.Q["join_interval_runs"](spark, d)) == {(a, b) for a, x, y in runs for b, u, v in runs if x < v and u < y}
