"""Language of web pages by Bayesian fusion of four kinds of evidence.

1. The text: byte trigrams of the visible text under a multinomial per
   language, fitted on labelled documents (a bounded sample); the likelihood is
   tempered, as neighbouring trigrams are not independent.
2. The language the markup declares.
3. The address: its top-level suffix with a short first path segment, if any.
4. The host's prior: counts of the host's other pages, smoothed towards its
   domain's, and those towards all pages'.

How far 2 and 3 can be trusted, and the priors, come from grouped sums of the
text posteriors over all pages, so a declaration that doesn't agree with the
texts loses its weight.  A page's own posterior is taken out of its host's and
domain's sums.  Sums are pre-aggregated before the shuffle, and the tables of
hosts join back under AQE, so a host with a third of all pages is no obstacle.

Defined results: missing or unreadable evidence is neutral; a page with none
gets the most likely language a priori; languages are those of the labelled
documents, and without any the language is null; repeated rows repeat; an empty
table gives no rows.
"""

from __future__ import annotations

import html as markup
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.llm.common import materialize

#: Rows for fitting the text model, and trigram slots.
FIT_ROWS = 6000
SLOTS = 1 << 16
#: Tempering of text likelihoods: a text counts as at most so many independent trigrams.
INDEPENDENT = 40.0
#: Pseudo-pages of the level above in each level's prior, and pseudo-counts of the evidence tables.
HOST_WEIGHT, DOMAIN_WEIGHT, EVIDENCE_WEIGHT = 4.0, 8.0, 2.0

_DROP = re.compile(r"(?is)<(script|style|noscript|template)\b.*?</\1\s*>|<!--.*?-->")
_TAG = re.compile(r"(?s)<[^>]*>")
_DECLARED = re.compile(r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-z]{2,3})")
_ADDRESS = re.compile(r"(?i)^(?:[a-z][a-z0-9+.-]*:)?//(?:[^/@]*@)?([^/:?#]+)[^/?#]*/?([^/?#]*)")


def visible_text(page: str) -> str:
    return markup.unescape(_TAG.sub(" ", _DROP.sub(" ", page)))


def address_parts(url: str | None) -> tuple[str | None, str | None, str | None]:
    """Host, registered domain (last two labels) and address suffix."""
    m = _ADDRESS.match(url or "")
    if not m:
        return None, None, None
    host = m[1].lower().rstrip(".")
    labels = host.split(".")
    segment = m[2].lower()
    hint = segment if 2 <= len(segment) <= 3 and segment.isalpha() else ""
    return host, ".".join(labels[-2:]), f"{labels[-1]}/{hint}"


def _trigrams(text: str) -> np.ndarray:
    b = np.frombuffer(" ".join(text.lower().split()).encode(), np.uint8).astype(np.uint32)
    if len(b) < 3:
        return np.zeros(0, np.int64)
    x = b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA77) + b[2:] * np.uint32(0xC2B2AE3D)
    return ((x ^ (x >> np.uint32(15))) % np.uint32(SLOTS)).astype(np.int64)


def fit_text(docs: DataFrame, lang: str = "lang", text: str = "text", key: str = "doc_id", max_rows: int = FIT_ROWS) -> tuple[list[str], np.ndarray]:
    """Languages and the log share of each trigram slot (languages x slots)."""
    rows = docs.where(docs[lang].isNotNull() & docs[text].isNotNull()).select(docs[key].alias("k"), docs[lang].alias("lang"), docs[text].alias("text"))
    total = rows.count()
    share = min(1.0, max_rows / max(total, 1))
    chosen = rows.where(F.pmod(F.xxhash64("k"), F.lit(1 << 20)) < int(share * (1 << 20)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for batch in batches:
            for lang, text in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                slots = np.bincount(_trigrams(text.as_py()), minlength=SLOTS)
                counts[lang] = counts.get(lang, 0) + slots
        for lang, c in counts.items():
            at = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at), pa.array(c[at].astype(np.int64))], names=["lang", "slot", "n"])

    got = chosen.mapInArrow(run, "lang string, slot long, n long").groupBy("lang", "slot").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(got["lang"].unique().tolist())
    table = np.full((len(langs), SLOTS), 0.1)
    for i, name in enumerate(langs):
        mine = got[got["lang"] == name]
        table[i, mine["slot"].to_numpy(np.int64)] += mine["n"].to_numpy()
    return langs, np.log(table / table.sum(axis=1, keepdims=True)) if langs else table


def _evidence(pages: DataFrame, langs: list[str], table: np.ndarray, key: str, url: str, html: str) -> DataFrame:
    """Per page its keys of evidence and text posterior under equal priors (null without text)."""
    # languages x slots: a size fixed by the label set
    shared = pages.sparkSession.sparkContext.broadcast(table.astype(np.float32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value.T.copy()
        for batch in batches:
            host, domain, suffix, declared, text = [], [], [], [], []
            for u, h in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                page = h.as_py() or ""
                a, b, c = address_parts(u)
                host.append(a)
                domain.append(b)
                suffix.append(c)
                d = _DECLARED.search(page)
                declared.append(d[1].lower() if d else None)
                slots = _trigrams(visible_text(page))
                if not len(slots):
                    text.append(None)
                    continue
                score = own[slots].mean(axis=0, dtype=np.float64) * min(len(slots), INDEPENDENT)
                p = np.exp(score - score.max())
                text.append((p / p.sum()).tolist())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.string()) for x in (host, domain, suffix, declared)), pa.array(text, pa.list_(pa.float64()))], names=["key", "host", "domain", "suffix", "declared", "text"])

    kind = pages.schema[key].dataType.simpleString()
    return pages.select(pages[key].alias("key"), pages[url].alias("url"), pages[html].alias("html")).mapInArrow(run, f"key {kind}, host string, domain string, suffix string, declared string, text array<double>")


def identify(pages: DataFrame, docs: DataFrame, key: str = "page_id", url: str = "url", html: str = "html", max_rows: int = FIT_ROWS) -> DataFrame:
    """Per row: key, language, probability, declared, host, text_language."""
    langs, table = fit_text(docs, max_rows=max_rows)
    if not langs:
        empty = F.lit(None).cast("string")
        return pages.select(key, empty.alias("language"), F.lit(None).cast("double").alias("probability"), empty.alias("declared"), empty.alias("host"), empty.alias("text_language"))
    n = len(langs)
    rows = materialize(_evidence(pages, langs, table, key, url, html))
    sums = [F.sum(F.col("text")[i]).alias(f"n{i}") for i in range(n)]

    def counted(name: str) -> DataFrame:
        known = rows.where(F.col(name).isNotNull() & F.col("text").isNotNull()).groupBy(F.col(name).alias(f"k_{name}")).agg(*sums)
        return known.select(f"k_{name}", F.array(*[F.col(f"n{i}") for i in range(n)]).alias(f"n_{name}"))

    whole = rows.agg(*[F.coalesce(s, F.lit(0.0)).alias(f"n{i}") for i, s in enumerate(sums)]).first()
    total = [float(x) for x in whole]
    prior = [(x + 1.0) / (sum(total) + n) for x in total]
    joined = rows
    for name in ("host", "domain", "suffix", "declared"):
        joined = joined.join(counted(name), F.col(name) == F.col(f"k_{name}"), "left").drop(f"k_{name}")
    zero = F.array(*[F.lit(0.0)] * n)
    own = F.coalesce("text", zero)
    counts = {name: F.coalesce(F.col(f"n_{name}"), own) for name in ("host", "domain", "suffix", "declared")}

    def others(name: str, i: int):
        return F.greatest(counts[name][i] - own[i], F.lit(0.0))

    def all_others(name: str):
        return sum((others(name, i) for i in range(n)), F.lit(0.0))

    logs = []
    for i in range(n):
        domain = (others("domain", i) + DOMAIN_WEIGHT * prior[i]) / (all_others("domain") + DOMAIN_WEIGHT)
        host = (others("host", i) + HOST_WEIGHT * domain) / (all_others("host") + HOST_WEIGHT)
        score = F.log(host) + F.log(F.greatest(own[i], F.lit(1e-12))) * F.when(F.col("text").isNotNull(), 1.0).otherwise(0.0)
        for name in ("suffix", "declared"):
            # P(evidence | language) up to a factor that all languages share
            given = (others(name, i) + EVIDENCE_WEIGHT * prior[i]) / (total[i] + EVIDENCE_WEIGHT)
            score = score + F.when(F.col(name).isNotNull(), F.log(given)).otherwise(0.0)
        logs.append(score)
    joined = joined.withColumn("logs", F.array(*logs))
    top = F.array_max("logs")
    names = F.array(*[F.lit(x) for x in langs])
    at = F.array_position("logs", top).cast("int")
    p = 1.0 / F.aggregate("logs", F.lit(0.0), lambda a, x: a + F.exp(x - top))
    text_at = F.array_position("text", F.array_max("text")).cast("int")
    return joined.select(F.col("key").alias(key), F.element_at(names, at).alias("language"), p.alias("probability"), "declared", "host", F.when(F.col("text").isNotNull(), F.element_at(names, text_at)).alias("text_language"))
