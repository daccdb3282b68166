"""Held-out accuracy of the quality classifier and of language identification; the pipeline's stages."""

import math
import os
import re
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rasterruns.llm import language_fusion, ordinal_quality, queries

LARGE = "/root/testdata/sf0.1"


@pytest.mark.skipif(not os.path.isdir(LARGE), reason="needs the larger tables")
def test_held_out_quality(spark):
    docs, labels = (spark.read.parquet(f"{LARGE}/{t}.parquet") for t in ("documents", "labels"))
    seen = labels.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(2)) == 0)
    got = ordinal_quality.scores(docs, seen).join(labels.join(seen.select("doc_id"), "doc_id", "left_anti"), "doc_id").toPandas()
    good = (got.quality == 1) & (got.toxic == 0)
    assert (got.kept == good).mean() > 0.97
    assert got.kept[good].mean() > 0.985 and got.kept[got.toxic == 1].mean() < 0.05
    assert got.expected_grade[good].mean() > got.expected_grade[(got.quality == 0) & (got.toxic == 0)].mean() > got.expected_grade[got.toxic == 1].mean()


def test_cumulative_link_gradient_and_order():
    rng = np.random.default_rng(0)
    rows = np.repeat(np.arange(400), 3)
    slots = rng.integers(0, 40, 1200)
    truth = rng.normal(size=40)
    score = np.bincount(rows, truth[slots])
    grades = np.digitize(score + rng.logistic(scale=0.3, size=400), [-1.0, 1.0])
    m = ordinal_quality.train(slots, np.ones(1200), rows, grades, 3)
    p = m.grades(np.bincount(rows, m.weights[slots]))
    assert np.allclose(p.sum(axis=1), 1) and m.thresholds[0] < m.thresholds[1]
    assert (p.argmax(axis=1) == grades).mean() > 0.8


def test_quality_hard_cases(spark):
    rows = [(1, None, "x"), (2, "", "x"), (None, "fine words here", None), (3, "w " * 20000, "x"), (3, "fine words here", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, c0 string").withColumn("_tail", F.lit(1))
    labels = spark.createDataFrame([(1, 1, 0), (3, 1, 0), (3, 0, None), (9, 0, 1)], "doc_id long, quality int, toxic int")
    got = ordinal_quality.scores(docs, labels).toPandas()
    assert len(got) == 5 and not got.kept[got.doc_id.isin([1, 2])].any()
    assert ordinal_quality.scores(docs, labels.limit(0)).where("kept").count() == 5
    assert ordinal_quality.select_good(docs, labels).columns == docs.columns
    assert ordinal_quality.scores(docs.limit(0), labels).count() == 0


def plain_features(text):
    """Slots and values of one text by the rule of the docstring, token by token."""
    tokens = (text or "").split()
    counts = defaultdict(int)
    for token in tokens:
        for w in re.findall(r"[^\W\d_]+", token.lower()):
            for n in (99, 5, 6, 7, 8):
                if n == 99 or len(w) > n:
                    counts[ordinal_quality._slot(f"{n}:{w[:n]}")] += 1
        case = "U" if token.isupper() and len(token) > 1 else "l"
        shape = re.sub(r"(.)\1+", r"\1+", re.sub(r"[^\W\d_]+", case, re.sub(r"\d+", "9", token)))
        counts[ordinal_quality._slot("s:" + shape[:12])] += 1
    if again := sum(a == b for a, b in zip(tokens, tokens[1:], strict=False)):
        counts[ordinal_quality._slot("r:")] += again
    out = {k: 6 * math.sqrt(c / len(tokens)) for k, c in counts.items()}
    if tokens:
        level = ordinal_quality._slot(f"v:{int(10 * len(set(tokens)) / len(tokens))}:{len(tokens).bit_length()}")
        out[level] = out.get(level, 0.0) + 1.0
    return out


def test_features_against_plain(spark, sf_dir, monkeypatch):
    texts = [r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("text").limit(300).collect()]
    texts += [None, "", " \t", "a a a b", "AB12!!! ab-cd_ef \u0130stanbul x\u00b2 ###", "word " * 5000]
    for cache, rows, size in ((300_000, 256, 1 << 15), (50, 7, 100), (0, 1, 1)):
        monkeypatch.setattr(ordinal_quality, "CACHE_TOKENS", cache)
        monkeypatch.setattr(ordinal_quality, "GROUP_ROWS", rows)
        monkeypatch.setattr(ordinal_quality, "GROUP_TOKENS", size)
        got = []
        for n, row, slot, value in ordinal_quality.Features().of(texts):
            part = [defaultdict(float) for _ in range(n)]
            for r, k, v in zip(row.tolist(), slot.tolist(), value.tolist(), strict=True):
                part[r][k] += v
            got += part
        assert len(got) == len(texts)
        for text, mine in zip(texts, got, strict=True):
            want = plain_features(text)
            assert mine.keys() == want.keys() and all(math.isclose(mine[k], v) for k, v in want.items())


def test_quality_against_plain(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    ratings = labels.select("doc_id", ordinal_quality.grade(F.col("quality"), F.col("toxic")).alias("grade"))
    model = ordinal_quality.fit(docs, ratings)
    again = ordinal_quality.fit(docs.repartition(5), ratings.repartition(3))
    assert np.allclose(model.weights, again.weights) and np.allclose(model.thresholds, again.thresholds)
    got = {r.doc_id: r for r in ordinal_quality.scores(docs, labels).collect()}
    for r in docs.select("doc_id", "text").limit(200).collect():
        score = sum(float(np.float32(model.weights[k])) * v for k, v in plain_features(r.text).items())
        below = [1 / (1 + math.exp(score - t)) for t in model.thresholds]
        tail, expected = 1 - below[-1], sum(1 - p for p in below)
        if not (r.text or "").split():
            tail = expected = 0.0
        mine = got[r.doc_id]
        assert math.isclose(mine.tail_probability, tail, abs_tol=1e-6) and math.isclose(mine.expected_grade, expected, abs_tol=1e-6)
        assert mine.kept == (mine.tail_probability >= ordinal_quality.CUTOFF)


def test_language_of_pages(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    truth = pages.toPandas().set_index("page_id").url.str.extract(r"//[^/]*/([a-z]{2})/")[0]
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    # the path's language segment was written with the page's language, so the model must not see it here
    blind = pages.withColumn("url", F.regexp_replace("url", r"(//[^/]*)/[a-z]{2}/", "$1/"))
    assert blind.where(F.col("url").rlike(r"//[^/]*/[a-z]{2}/")).count() == 0
    for got, least in ((queries.op10_language_fusion(spark, sf_dir).toPandas(), 0.97), (language_fusion.identify(blind, docs).toPandas(), 0.95)):
        assert len(got) == len(truth)
        both = pd.concat([got.set_index("page_id").language, truth], axis=1).dropna()
        assert (both.iloc[:, 0] == both.iloc[:, 1]).mean() > least
        assert got.probability.between(0.25, 1.0 + 1e-9).all()


def test_language_against_plain(spark, sf_dir):
    """The fused posterior page by page, from counts kept in dictionaries."""
    docs, pages = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "pages"))
    extra = spark.createDataFrame([(-1, None, None), (-2, "nonsense", "<html lang=xx>"), (-3, "http://lone.example/fr/a", "")], "page_id long, url string, html string")
    pages = pages.select("page_id", "url", "html").unionByName(extra)
    langs, table = language_fusion.fit_text(docs)
    table, n, rows = table.astype(np.float32), len(langs), []
    for r in pages.collect():
        page = r.html or ""
        slots = language_fusion._trigrams(language_fusion.visible_text(page))
        text = None
        if len(slots):
            logs = [float(np.mean(table[i][slots], dtype=np.float64)) * min(len(slots), language_fusion.INDEPENDENT) for i in range(n)]
            odds = [math.exp(x - max(logs)) for x in logs]
            text = [x / sum(odds) for x in odds]
        declared = language_fusion._DECLARED.search(page)
        rows.append((r.page_id, *language_fusion.address_parts(r.url), declared and declared[1].lower(), text))
    counts = [Counter() for _ in range(4)]
    total = [0.0] * n
    for _, *keys, text in rows:
        for i in range(n) if text else ():
            total[i] += text[i]
            for table_of, k in zip(counts, keys, strict=True):
                table_of[k, i] += text[i]
    prior = [(x + 1) / (sum(total) + n) for x in total]
    got = {r.page_id: r for r in language_fusion.identify(pages, docs).collect()}
    assert len(got) == len(rows)
    for page, *keys, text in rows:
        own = text or [0.0] * n
        # what the other pages with the same host, domain, suffix and declaration say
        other = [[max(c[k, i] - own[i], 0.0) if k is not None else 0.0 for i in range(n)] for c, k in zip(counts, keys, strict=True)]
        logs = []
        for i in range(n):
            domain = (other[1][i] + language_fusion.DOMAIN_WEIGHT * prior[i]) / (sum(other[1]) + language_fusion.DOMAIN_WEIGHT)
            host = (other[0][i] + language_fusion.HOST_WEIGHT * domain) / (sum(other[0]) + language_fusion.HOST_WEIGHT)
            x = math.log(host) + (math.log(max(own[i], 1e-12)) if text else 0.0)
            for seen, k in zip(other[2:], keys[2:], strict=True):
                if k is not None:
                    x += math.log((seen[i] + language_fusion.EVIDENCE_WEIGHT * prior[i]) / (total[i] + language_fusion.EVIDENCE_WEIGHT))
            logs.append(x)
        best = max(logs)
        p = 1 / sum(math.exp(x - best) for x in logs)
        assert math.isclose(got[page].probability, p, rel_tol=1e-6), page
        if sum(best - x < 1e-9 for x in logs) == 1:
            assert got[page].language == langs[logs.index(best)]


def test_language_hard_cases(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    en, fr = ([r.text for r in docs.where(F.col("lang") == x).limit(4).collect()] for x in ("en", "fr"))
    rows = [(1, "http://a.example.com/x", f"<html lang=fr><p>{en[0]}</p>"), (2, None, None), (None, "nonsense", "<html lang='fr'>"), (3, "https://b.example.org/fr/1", f"<html lang=\"fr\"><script>{en[1]}</script><p>{fr[0]}"), (3, "https://b.example.org/fr/1", f"<html lang=\"fr\"><script>{en[1]}</script><p>{fr[0]}"), (4, "//user@h.:80", "<p>" + fr[1] * 50)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("key", F.lit("x"))
    got = language_fusion.identify(pages, docs).toPandas()
    assert len(got) == 6 and set(got.language[got.page_id == 3]) == {"fr"} and set(got.language[got.page_id == 4]) == {"fr"}
    assert language_fusion.identify(pages, docs.limit(0)).where("language is null").count() == 6
    assert language_fusion.identify(pages.limit(0), docs).count() == 0
    assert language_fusion.address_parts("https://u@WWW.Example.com:8/en/x") == ("www.example.com", "example.com", "com/en")


def test_pipeline_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, kept = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, sf_dir)
        assert kept.columns == columns, name
    n = kept.count()
    last = corpus_pipeline.STAGES[-1][1](spark, kept, sf_dir)
    assert last.count() == n == corpus_pipeline.run(spark, sf_dir).count()
    odd = docs.limit(20).withColumn("_tail", F.lit(1)).withColumn("comp", F.lit("c")).withColumn("_k", F.lit("c"))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, odd, sf_dir).columns == odd.columns, name
        assert stage(spark, odd.limit(0), sf_dir).count() == 0
