"""Quality by ordinal cumulative-link regression on hashed text.

Ratings are graded: toxic (0), poor (1), good (2).  One weight vector is shared
by all grades and ordered thresholds cut its score, so P(grade <= k) is the
logistic of threshold k less the score; this gives an expected grade and the
tail probability of the top grade, by which documents are selected.

Features are hashed into a table of fixed size: words, their beginnings and
token shapes (letter case, digits and trailing symbols), each by the square
root of its share of the text's tokens, so is the share of tokens that repeat
the one before, and the level of word variety at the
text's length.  The whole text counts.

Training takes labelled documents chosen by a hash of the id, at most
``max_rows`` of them (a documented bound of the fit only); their features, not
their texts, reach the driver.  Scoring broadcasts the weight table (fixed size).

Defined results: a document without words has expected grade and tail 0 and is
rejected; without any labelled document the scores are null and all are kept;
several ratings of a document count as the lowest; ratings with nulls are
ignored; repeated rows are scored alike; an empty table gives no rows.
"""

from __future__ import annotations

import re
from array import array
from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import islice, pairwise
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_64_intdigest

from rasterruns.llm.common import sliced

BITS = 18
MAX_ROWS = 6_000
CUTOFF = 0.5
#: Tokens remembered by one task at most.
CACHE_TOKENS = 300_000
#: Texts, and different tokens of texts, whose features are computed together (a longer text is a group by itself).
GROUP_ROWS, GROUP_TOKENS = 256, 1 << 15
_COUNT_BITS = 36
_SCALE = 6.0
#: Lengths of the word beginnings that count besides the whole word (99).
_PREFIXES = (99, 5, 6, 7, 8)
_WORD = re.compile(r"[^\W\d_]+")
_DIGITS = re.compile(r"\d+")
_RUNS = re.compile(r"(.)\1+")


def _slot(name: str) -> int:
    return xxh3_64_intdigest(name) & ((1 << BITS) - 1)


class Features(dict):
    """Numbers tokens; number i has the slots ``_slots[_starts[i]:_starts[i + 1]]`` (of its words, their beginnings and its shape)."""

    def __init__(self):
        self._slots, self._starts = array("i"), array("q", [0])

    def __missing__(self, token: str) -> int:
        low, case = token.lower(), "U" if token.isupper() and len(token) > 1 else "l"
        for w in (low,) if low.isalpha() else _WORD.findall(low):
            self._slots.extend([_slot(f"{n}:{w[:n]}") for n in _PREFIXES if n == 99 or len(w) > n])
        shape = case if token.isalpha() else _RUNS.sub(r"\1+", _WORD.sub(case, _DIGITS.sub("9", token)))
        self._slots.append(_slot("s:" + shape[:12]))
        self._starts.append(len(self._slots))
        out = self[token] = len(self)
        return out

    def of(self, texts: Iterable[str | None]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """Texts -> groups ``(texts in it, row, slot, value)``, rows counted from 0 in each group; none for a text without tokens.

        A slot may stand twice in a row; its values add up.
        """
        held: list[tuple[list[str], Counter]] = []
        size = 0
        for text in texts:
            tokens = (text or "").split()
            held.append((tokens, counts := Counter(tokens)))
            size += len(counts)
            if size >= GROUP_TOKENS or len(held) == GROUP_ROWS:
                yield len(held), *self._together(held)
                held, size = [], 0
        if held:
            yield len(held), *self._together(held)

    def _together(self, held: list[tuple[list[str], Counter]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if len(self) >= CACHE_TOKENS:
            self.clear()
            self._slots, self._starts = array("i"), array("q", [0])
        size = np.array([len(counts) for _, counts in held], np.int64)
        number = np.fromiter((self[t] for _, counts in held for t in counts), np.int64, size.sum())
        count = np.fromiter((c for _, counts in held for c in counts.values()), np.int64, size.sum())
        length = np.array([len(tokens) for tokens, _ in held], np.int64)
        again = np.array([sum(map(eq, tokens, islice(tokens, 1, None))) for tokens, _ in held], np.int64)
        some = np.flatnonzero(length)
        # row, slot and count in one number, so that a plain sort brings the equal slots of a row together
        start = np.frombuffer(self._starts, np.int64)[number]
        n = np.frombuffer(self._starts, np.int64)[number + 1] - start
        place = np.arange(n.sum()) + np.repeat(start - (np.cumsum(n) - n), n)
        packed = np.repeat((np.repeat(np.arange(len(held)), size) << (BITS + _COUNT_BITS)) | count, n)
        packed |= np.frombuffer(self._slots, np.int32)[place].astype(np.int64) << _COUNT_BITS
        rerun = np.flatnonzero(again)
        packed = np.concatenate([packed, (((rerun << BITS) | _slot("r:")) << _COUNT_BITS) | again[rerun]])
        packed.sort()
        at = packed >> _COUNT_BITS
        head = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])) if len(at) else at
        total = np.add.reduceat(packed & ((1 << _COUNT_BITS) - 1), head) if len(at) else at
        row, slot = at[head] >> BITS, at[head] & ((1 << BITS) - 1)
        value = _SCALE * np.sqrt(total / length[row])
        level = [_slot(f"v:{int(10 * size[i] / length[i])}:{int(length[i]).bit_length()}") for i in some.tolist()]
        row, slot, value = np.concatenate([row, some]), np.concatenate([slot, np.array(level, np.int64)]), np.concatenate([value, np.ones(len(some))])
        order = np.argsort(row, kind="stable")
        return row[order], slot[order], value[order]


def grade(quality: Column, toxic: Column) -> Column:
    """0 toxic, 1 poor, 2 good; null if a rating is missing."""
    return F.when(toxic == 1, 0).when((toxic == 0) & (quality == 0), 1).when((toxic == 0) & (quality == 1), 2)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class Model:
    """Weights over the table and ascending thresholds between grades."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray):
        self.weights, self.thresholds = weights, thresholds

    def grades(self, scores: np.ndarray) -> np.ndarray:
        """Probability of each grade, a row a score."""
        below = _sigmoid(self.thresholds[None, :] - scores[:, None])
        edge = np.concatenate([np.zeros((len(scores), 1)), below, np.ones((len(scores), 1))], axis=1)
        return np.diff(edge, axis=1)


def train(slots: np.ndarray, values: np.ndarray, rows: np.ndarray, grades: np.ndarray, levels: int, steps: int = 220, rate: float = 0.15, ridge: float = 5e-4, least_rows: int = 5) -> Model:
    """Maximum likelihood with a ridge, by full-batch Adam; ``rows`` ascend and index ``grades``."""
    n = len(grades)
    seen = np.bincount(slots, minlength=1 << BITS)
    used = np.flatnonzero(seen >= least_rows)
    index = np.full(1 << BITS, -1)
    index[used] = np.arange(len(used))
    keep = index[slots] >= 0
    slots, values, rows = index[slots[keep]], values[keep].astype(np.float64), rows[keep].astype(np.intp)
    w = np.zeros(len(used))
    below = np.cumsum(np.bincount(grades, minlength=levels))[:-1] / n
    cut = np.log(np.clip(below, 1e-3, 1 - 1e-3) / np.clip(1 - below, 1e-3, 1 - 1e-3))
    cut = np.maximum.accumulate(cut + 1e-3 * np.arange(levels - 1))
    free = np.concatenate([cut[:1], np.log(np.maximum(np.diff(cut), 1e-3))])  # first threshold, log gaps
    m = [np.zeros_like(w), np.zeros_like(free)]
    v = [np.zeros_like(w), np.zeros_like(free)]
    for step in range(1, steps + 1):
        cut = free[0] + np.concatenate([[0.0], np.cumsum(np.exp(free[1:]))])
        score = np.bincount(rows, weights=values * w[slots], minlength=n)
        s = _sigmoid(np.concatenate([np.full((n, 1), -40.0), cut[None, :] - score[:, None], np.full((n, 1), 40.0)], axis=1))
        at = np.arange(n)
        hi, lo = s[at, grades + 1], s[at, grades]
        p = np.maximum(hi - lo, 1e-9)
        dh, dl = hi * (1 - hi) / p, lo * (1 - lo) / p
        g_score = (dh - dl) / n  # of the negative log-likelihood
        g_cut = np.zeros(levels + 1)
        np.add.at(g_cut, grades + 1, -dh / n)
        np.add.at(g_cut, grades, dl / n)
        g_cut = g_cut[1:-1]
        tail = np.cumsum(g_cut[::-1])[::-1]
        grads = [np.bincount(slots, weights=values * g_score[rows], minlength=len(w)) + ridge * w / 10, np.concatenate([tail[:1], tail[1:] * np.exp(free[1:])])]
        for k, (x, g) in enumerate(((w, grads[0]), (free, grads[1]))):
            m[k] = 0.9 * m[k] + 0.1 * g
            v[k] = 0.99 * v[k] + 0.01 * g * g
            x -= rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
    full = np.zeros(1 << BITS)
    full[used] = w
    return Model(full, free[0] + np.concatenate([[0.0], np.cumsum(np.exp(free[1:]))]))


def fit(docs: DataFrame, ratings: DataFrame, key: str = "doc_id", text: str = "text", max_rows: int = MAX_ROWS) -> Model | None:
    """``ratings(key, grade)`` -> model; None without a rated document."""
    rated = ratings.where("grade is not null").groupBy(F.col(key).alias("k")).agg(F.min("grade").alias("grade"))
    total = rated.count()
    if not total:
        return None
    # the rows of the smallest hashes, so that any partitioning fits the same model; the range beforehand keeps the sort small
    share = min(1.0, (max_rows + 6 * max_rows**0.5) / total)
    draw = F.pmod(F.xxhash64("k"), F.lit(1 << 40))
    chosen = rated.where(draw < int(share * (1 << 40))).orderBy(draw, "k").limit(max_rows)
    rows = docs.select(docs[key].alias("k"), docs[text].alias("text")).join(chosen, "k").select("k", "grade", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Features()
        for batch in sliced(batches):
            slots, values = [], []
            for n, row, slot, value in features.of(t.as_py() for t in batch.column(2)):
                edges = np.searchsorted(row, np.arange(n + 1)).tolist()
                slots += [slot[a:b].astype(np.int32).tobytes() for a, b in pairwise(edges)]
                values += [value[a:b].astype(np.float32).tobytes() for a, b in pairwise(edges)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(slots, pa.binary()), pa.array(values, pa.binary())], names=["k", "grade", "slots", "values"])

    kind = rows.schema["k"].dataType.simpleString()
    got = rows.mapInArrow(run, f"k {kind}, grade int, slots binary, values binary").toPandas().sort_values("k", kind="stable")
    if not len(got):
        return None
    slots = np.frombuffer(b"".join(got.pop("slots")), np.int32)
    values = np.frombuffer(b"".join(got["values"]), np.float32)
    row = np.repeat(np.arange(len(got), dtype=np.int32), [len(x) // 4 for x in got.pop("values")])
    grades = got["grade"].to_numpy(np.int64)
    return train(slots, values, row, grades, max(2, int(grades.max()) + 1))


def _scored(docs: DataFrame, model: Model, text: str) -> DataFrame:
    """``docs`` with ``_expected`` and ``_tail``; one pass, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weights.astype(np.float32), model.thresholds))
    at = docs.columns.index(text)
    rows = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])
    schema = ", ".join(f"`{c}` {t}" for c, t in rows.dtypes) + ", _expected double, _tail double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, thresholds = shared.value
        own, features = Model(weights, thresholds), Features()
        for batch in sliced(batches):
            scores, filled = [np.zeros(0)], [np.zeros(0, bool)]
            for n, row, slot, value in features.of(t.as_py() for t in batch.column(at)):
                scores.append(np.bincount(row, weights=weights[slot] * value, minlength=n))
                filled.append(np.bincount(row, minlength=n) > 0)
            score, some = np.concatenate(scores), np.concatenate(filled)
            p = own.grades(score)
            expected, tail = np.where(some, p @ np.arange(p.shape[1]), 0.0), np.where(some, p[:, -1], 0.0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(expected), pa.array(tail)], names=[*batch.schema.names, "_expected", "_tail"])

    return rows.mapInArrow(run, schema)


def _with_model(docs: DataFrame, labels: DataFrame, key: str, text: str, max_rows: int) -> DataFrame:
    ratings = labels.select(F.col(key), grade(F.col("quality"), F.col("toxic")).alias("grade"))
    model = fit(docs, ratings, key, text, max_rows)
    if model is None:
        return docs.toDF(*[f"c{i}" for i in range(len(docs.columns))]).withColumn("_expected", F.lit(None).cast("double")).withColumn("_tail", F.lit(None).cast("double"))
    return _scored(docs, model, text)


def scores(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", cutoff: float = CUTOFF, max_rows: int = MAX_ROWS) -> DataFrame:
    """Per row: key, expected_grade, tail_probability (of the top grade), kept."""
    out = _with_model(docs.select(key, text), labels, key, text, max_rows)
    return out.select(F.col("c0").alias(key), F.col("_expected").alias("expected_grade"), F.col("_tail").alias("tail_probability"), F.coalesce(F.col("_tail") >= cutoff, F.lit(True)).alias("kept"))


def select_good(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", cutoff: float = CUTOFF, max_rows: int = MAX_ROWS) -> DataFrame:
    """The documents whose tail probability reaches the cutoff, with all their columns."""
    out = _with_model(docs, labels, key, text, max_rows).where(F.coalesce(F.col("_tail") >= cutoff, F.lit(True)))
    return out.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)])
