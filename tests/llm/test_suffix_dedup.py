"""Suffix arrays and repeated passages against brute force."""

import hashlib
import random
from collections import Counter

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rasterruns.llm import queries, suffix_dedup
from rasterruns.llm.suffix_array import suffix_array


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(0, 3), max_size=60))
def test_suffix_array_small(text):
    assert suffix_array(text) == sorted(range(len(text)), key=lambda i: text[i:])


def test_suffix_array_of_repeats():
    for text in (b"a" * 500, b"ab" * 300, b"abracadabra" * 40, b"", b"x", bytes(range(256)) * 2):
        assert suffix_array(text) == sorted(range(len(text)), key=lambda i: text[i:])


def brute(rows, span=50):
    first = {}
    for i, t in rows:
        if i is not None:
            b = (t or "").encode()
            for k in range(len(b) - span + 1):
                w = b[k : k + span]
                first[w] = min(first.get(w, i), i)
    out = Counter()
    for i, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        if i is not None:
            for k in range(len(b) - span + 1):
                if first[b[k : k + span]] < i:
                    gone[k : k + span] = b"\1" * span
        rest = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        spans = sum(1 for k, g in enumerate(gone) if g and (k == 0 or not gone[k - 1]))
        out[(i, len(b), sum(gone), spans, hashlib.sha256(rest).hexdigest())] += 1
    return out


def test_whole_table_equals_brute_force(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = Counter(tuple(r) for r in queries.op8_suffix_dedup(spark, sf_dir).collect())
    assert got == brute([(r.doc_id, r.text) for r in docs.collect()])


@pytest.mark.parametrize("hot", [4096, 3])
def test_hard_cases(spark, monkeypatch, hot):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    rnd = random.Random(3)
    word = lambda n: "".join(rnd.choice("abcdefgh é") for _ in range(n))
    passage, rows = word(400), []
    for i in range(60):
        a, b = sorted((rnd.randrange(400), rnd.randrange(400)))
        rows.append((rnd.randrange(-20, 40), word(rnd.randrange(80)) + passage[a:b] + word(rnd.randrange(80))))
    rows += [(100, "a" * 300), (101, "a" * 49), (102, "a" * 50), (103, "ab" * 200), (99, "ab" * 100), (None, passage), (104, None), (105, ""), (106, passage), (106, passage), (106, passage[:200] + "!"), (107, "word " * 9000), (108, "word " * 9000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as doc", "'x' as starts")
    monkeypatch.setattr(suffix_dedup, "SORT_BYTES", 4000)
    got = Counter(tuple(r) for r in suffix_dedup.removal_digests(docs).collect())
    assert got == brute(rows)
    kept = suffix_dedup.without_repeats(docs)
    assert kept.columns == docs.columns and kept.count() == len(rows)
    assert suffix_dedup.removal_digests(docs.limit(0)).count() == 0
