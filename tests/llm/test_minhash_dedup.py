"""Near-duplicate documents against all pairs."""

import math
import random
import re
from collections import Counter, defaultdict

import pytest

from rasterruns.llm import minhash_dedup, queries


def brute(rows, k, percent):
    def sets(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()

    s = [(i, sets(t)) for i, t in rows]
    index, near = defaultdict(list), defaultdict(set)
    for n, (i, x) in enumerate(s):
        if i is None:
            continue
        hits = Counter(m for g in x for m in index[g])
        for m, both in hits.items():
            j, y = s[m]
            if 100 * both >= percent * (len(x) + len(y) - both):
                near[i].add(j)
                near[j].add(i)
        for g in x:
            index[g].append(n)
    root = {}
    for i in sorted({i for i, _ in rows if i is not None}):
        todo = [i]
        while todo:
            if (v := todo.pop()) not in root:
                root[v] = i
                todo += near[v]
    return Counter((i, len(x), root.get(i), i is None or root[i] == i) for i, x in s)


def test_whole_table_equals_all_pairs(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = Counter(tuple(r) for r in queries.op2_minhash_dedup(spark, sf_dir).collect())
    assert got == brute([(r.doc_id, r.text) for r in docs.collect()], 3, 85)


@pytest.mark.parametrize("small,block", [(48, 8 << 20), (2, 4000)])
def test_families_and_hard_cases(spark, monkeypatch, small, block):
    monkeypatch.setattr(minhash_dedup, "SMALL_BUCKET", small)
    monkeypatch.setattr(minhash_dedup, "BLOCK_BYTES", block)
    rnd = random.Random(8)
    word = lambda: "".join(rnd.choice("abcdefg") for _ in range(3))
    rows = []
    for f in range(4):  # families whose members differ in more and more places
        base = [word() for _ in range(120)]
        for m in range(30):
            t = list(base)
            for _ in range(rnd.randrange(6)):
                t[rnd.randrange(120)] = word()
            rows.append((rnd.randrange(10_000), " ".join(t)))
    rows += [(20_000, None), (20_001, ""), (20_002, " \t\n"), (20_003, "Ab cd"), (20_004, "aB\ncd"), (20_005, "É a b"), (20_006, "é a b"), (None, "x y z"), (None, None), (20_007, "x y z"), (20_008, "w " * 9000), (20_009, "w " * 8000), (20_010, "a b c d"), (20_010, "p q r s"), (20_011, "P q r s"), (20_012, "a b c d"), (20_012, "a b c d")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as node", "'s' as sid", "2 as doc")
    for k, percent in ((3, 85), (5, 80)):
        got = Counter(tuple(r) for r in minhash_dedup.near_duplicates(docs, k, percent).collect())
        assert got == brute(rows, k, percent)
    assert minhash_dedup.without_near_duplicates(docs).columns == docs.columns
    assert minhash_dedup.near_duplicates(docs.limit(0)).count() == 0


@pytest.mark.parametrize("percent", [80, 85])
def test_gate_loses_less_than_bands(percent):
    p, n = percent / 100, minhash_dedup.BANDS * minhash_dedup.ROWS
    least = p - minhash_dedup.MARGIN
    gate = sum(math.comb(n, k) * p**k * (1 - p) ** (n - k) for k in range(n + 1) if k / n < least)
    assert gate < (1 - p**minhash_dedup.ROWS) ** minhash_dedup.BANDS
