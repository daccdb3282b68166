"""Removing passages that an earlier document holds, by suffix arrays.

A byte goes if a string of SPAN bytes that covers it also starts in a document
with a smaller id.  Candidates come from content-chosen anchors: every window
of SPAN bytes belongs to the anchor it picks, equal windows pick equal anchors,
so only stretches whose anchor hash stands in two documents can share a window.

1. Anchor hashes are counted by document (pre-aggregated minimum and maximum);
   occurrences of hashes that stand in two documents stay.
2. Equal stretches form a class; all its documents but the first lose the whole
   stretch, and only the first one's stretch goes on.  So a passage in a third
   of all documents goes on once.
3. Different classes of one anchor hash meet in a task (an anchor with very many
   classes is first dealt by longer strings around it).  Their stretches are
   cut to the windows whose inner bytes occur twice, joined, and suffix-sorted
   by grouping (suffix_array).  Neighbours in suffix order that agree on a whole
   window share it, and the least document among them keeps it.
4. The runs found are gathered by document and cut out of its text.

Defined results: null text counts as empty; a document shorter than a window
stays whole; rows with the same id are one document's texts (nothing matches
between them, each row is cut by itself); rows without an id stay whole and
take no part; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.llm import anchors
from rasterruns.llm.anchors import BEFORE, SPAN
from rasterruns.llm.common import materialize, release, sliced
from rasterruns.llm.suffix_array import suffix_array

#: Stretch bytes that are filtered at once, and joined bytes that are suffix-sorted at once, small enough for a
#: processor's cache (both in whole anchor groups, so a group may exceed them).
SORT_BYTES = 1 << 18
TEXT_BYTES = 1 << 13
#: Classes of an anchor beyond which its stretches are dealt by finer hashes first.
HOT = 4096
#: Leads whose windows are filtered together, by the bytes they all hold.
_STEP = 4
_WIDTH = BEFORE + SPAN
_GAP = 1 << 40  # between the texts of one id


def _grouped(docs: DataFrame, key: str, text: str) -> tuple[DataFrame, bool]:
    """``(doc, texts)``, one row per id, and whether ids repeat; ids that stand once need no shuffle."""
    rows = docs.where(docs[key].isNotNull()).select(docs[key].cast("long").alias("doc"), docs[text].alias("text"))
    ids = rows.select("doc").groupBy("doc").agg(F.count(F.lit(1)).alias("n"))
    repeats = ids.where("n > 1").limit(1).count()
    if not repeats:
        return rows.select("doc", F.array("text").alias("texts")), False
    return rows.groupBy("doc").agg(F.array_sort(F.collect_set(F.coalesce("text", F.lit("")))).alias("texts")), True


def _texts(column: pa.Array) -> list[list[bytes]]:
    return [[(t or "").encode() for t in ts] for ts in column.to_pylist()]


def _anchors(grouped: DataFrame, places: bool) -> DataFrame:
    """``(h, doc)`` of every anchor, with the stretch hash ``c`` and the place ``at`` if asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            ids = batch.column(0).to_numpy()
            many = _texts(batch.column(1))
            flat = [t for ts in many for t in ts]
            owner = np.array([i for i, ts in enumerate(many) for _ in ts], np.int64)
            part = np.array([j for ts in many for j in range(len(ts))], np.int64)
            for number, place, h, c in anchors.anchor_batch(flat, places):
                columns = [pa.array(h), pa.array(ids[owner[number]])]
                if places:
                    columns += [pa.array(c), pa.array(place + (part[number] * _GAP << 10))]
                yield pa.RecordBatch.from_arrays(columns, names=["h", "doc", "c", "at"][: len(columns)])

    return grouped.mapInArrow(run, "h long, doc long" + ", c long, at long" * places)


def _stretches(grouped: DataFrame, places: DataFrame) -> DataFrame:
    """Cut the stretch at each place ``(h, doc, at)`` out of its text."""
    by_doc = places.groupBy("doc").agg(F.collect_list(F.struct("h", "at")).alias("places"))
    joined = grouped.join(by_doc, "doc").select("doc", "texts", "places")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            many = _texts(batch.column(1))
            column = batch.column(2)
            sizes = column.value_lengths().to_numpy()
            flat = column.flatten()
            h, at = flat.field(0), flat.field(1).to_numpy()
            row = np.repeat(np.arange(len(many)), sizes)
            place, longest, shortest = anchors.unpack(at)
            part, inside = place // _GAP, place % _GAP
            cut = [many[r][k][a - lo : a + SPAN - hi] for r, k, a, lo, hi in zip(row.tolist(), part.tolist(), inside.tolist(), longest.tolist(), shortest.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([h, pa.array(batch.column(0).to_numpy()[row]), flat.field(1), pa.array(cut, pa.binary())], names=["h", "doc", "at", "stretch"])

    return joined.mapInArrow(run, "h long, doc long, at long, stretch binary")


def _shared_leads(h: np.ndarray, doc: np.ndarray, longest: np.ndarray, shortest: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per stretch the longest and shortest lead whose windows may be shared (longest -1: none), and the hash of what they hold.

    ``rows``: the stretches as byte rows with their anchors in one column.  A
    step of leads passes if the bytes common to its windows occur with the same
    anchor in another document.
    """
    words = anchors._TC[rows]
    with np.errstate(over="ignore"):
        up, _ = anchors._power_pair(1 << 10)
        sums = np.concatenate([np.zeros((len(rows), 1), np.uint64), np.cumsum(words * up[:_WIDTH], axis=1)], axis=1)
        far, near = np.full(len(rows), -1), np.full(len(rows), BEFORE + 1)
        for low in range(0, BEFORE + 1, _STEP):
            high = min(low + _STEP - 1, BEFORE)
            has = np.flatnonzero((longest >= low) & (shortest <= high))
            if not len(has):
                continue
            key = (sums[has, _WIDTH - high] - sums[has, BEFORE - low]) ^ (h[has].view(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            order = np.argsort(key, kind="stable")
            new = np.flatnonzero(np.concatenate([[True], np.diff(key[order]) != 0]))
            docs = doc[has][order]
            many = np.minimum.reduceat(docs, new) < np.maximum.reduceat(docs, new)
            ok = has[order[np.repeat(many, np.diff(np.append(new, len(order))))]]
            far[ok] = np.maximum(far[ok], np.minimum(high, longest[ok]))
            near[ok] = np.minimum(near[ok], np.maximum(low, shortest[ok]))
        held = sums[np.arange(len(rows)), _WIDTH - np.minimum(near, BEFORE)] - sums[np.arange(len(rows)), BEFORE - np.maximum(far, 0)]
        names = anchors.mixed(held ^ anchors.mixed(h.view(np.uint64) + ((far.astype(np.uint64) << np.uint64(8)) | near.astype(np.uint64))))
    return far, near, names


def _stretches_of_groups(h: np.ndarray, ends: np.ndarray) -> list[tuple[int, int]]:
    """Cut joined stretches between anchor groups into texts of about TEXT_BYTES."""
    last = np.append(np.flatnonzero(np.diff(h)), len(h) - 1)
    cuts = [0]
    for e in ends[last].tolist():
        if e - cuts[-1] >= TEXT_BYTES:
            cuts.append(e)
    if cuts[-1] < ends[-1]:
        cuts.append(int(ends[-1]))
    return list(zip(cuts[:-1], cuts[1:], strict=True))


def shared_runs(h: np.ndarray, doc: np.ndarray, at: np.ndarray, stretches: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(doc, start, end)`` of the runs that each stretch shares with a smaller document's."""
    place, longest, shortest = anchors.unpack(at)
    rows = np.zeros((len(stretches), _WIDTH), np.uint8)
    lengths = np.array([len(s) for s in stretches], np.int64)
    flat = np.frombuffer(b"".join(stretches), np.uint8)
    row = np.repeat(np.arange(len(stretches)), lengths)
    column = np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths) + (BEFORE - longest)[row]
    rows[row, column] = flat
    far, near, names = _shared_leads(h, doc, longest, shortest, rows)
    keep = np.flatnonzero(far >= 0)
    if not len(keep):
        return (np.zeros(0, np.int64),) * 3
    # what is left of the stretches may be equal now: again the first document's goes on
    order = keep[np.lexsort((doc[keep], names[keep]))]
    head = np.flatnonzero(np.concatenate([[True], names[order[1:]] != names[order[:-1]]]))
    later = doc[order] > np.repeat(doc[order[head]], np.diff(np.append(head, len(order))))
    whole = order[later]
    known = doc[whole], place[whole] - far[whole], place[whole] - near[whole] + SPAN
    keep = np.sort(order[~later])
    far, near = far[keep], near[keep]
    size = SPAN + far - near + 1  # with a separator
    ends = np.cumsum(size)
    owner = np.repeat(np.arange(len(keep)), size)
    within = np.arange(ends[-1]) - (ends - size)[owner]
    text = np.where(within == size[owner] - 1, 0, rows[keep[owner], np.minimum((BEFORE - far)[owner] + within, _WIDTH - 1)].astype(np.int64) + 1)
    order = np.concatenate([a + np.array(suffix_array(text[a:b]), np.int64) for a, b in _stretches_of_groups(h[keep], ends)])
    order = order[(within[order] + SPAN) < size[owner[order]]]  # whole windows only
    windows = np.lib.stride_tricks.sliding_window_view(text.astype(np.uint16), SPAN)
    new = np.concatenate([[True], (windows[order[1:]] != windows[order[:-1]]).any(axis=1)])
    heads = np.flatnonzero(new)
    docs = doc[keep][owner[order]]
    least = np.repeat(np.minimum.reduceat(docs, heads), np.diff(np.append(heads, len(order))))
    hit = order[docs > least]
    hit.sort()
    if not len(hit):
        return known
    # neighbouring windows of one stretch make one run
    opens = np.concatenate([[True], (np.diff(hit) != 1) | (np.diff(owner[hit]) != 0)])
    a, b = hit[opens], hit[np.append(np.flatnonzero(opens)[1:], len(hit)) - 1]
    who = owner[a]
    start = place[keep[who]] - far[who] + within[a]
    return tuple(np.concatenate(x) for x in zip(known, (doc[keep[who]], start, start + (b - a) + SPAN), strict=True))


def _sorted_runs(stretches: DataFrame) -> DataFrame:
    """Suffix-sort the stretches of each anchor group."""
    names = ["doc", "start", "end"]

    def work(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(held)
        h, doc, at = (t.column(j).to_numpy() for j in range(3))
        return pa.RecordBatch.from_arrays([pa.array(x) for x in shared_runs(h, doc, at, t.column(3).to_pylist())], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, last = [], 0, None
        for batch in batches:
            h = batch.column(0).to_numpy()
            if not len(h):
                continue
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(h)) + 1, [len(h)]])
            a = 0
            for b in cuts[1:].tolist():
                # whole groups; a group may go on in the next batch
                if size + (b - a) * _WIDTH > SORT_BYTES or b == len(h):
                    if held and size + (b - a) * _WIDTH > SORT_BYTES and h[a] != last:
                        yield work(held)
                        held, size = [], 0
                    held.append(batch.slice(a, b - a))
                    size, last, a = size + (b - a) * _WIDTH, h[b - 1], b
        if held:
            yield work(held)

    return stretches.repartition("h").sortWithinPartitions("h").mapInArrow(run, "doc long, start long, end long")


def _split_hot(stretches: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Deal anchors with very many classes by the bytes that the windows of a lead step share.

    Returns runs that are sure and the stretches, shorter and under finer
    hashes, that go on.  Equal windows share anchor, step and inner bytes, so
    none is lost; equal pieces are one class again before anything is sorted.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h, doc, at = (batch.column(j).to_numpy() for j in range(3))
            place, longest, shortest = anchors.unpack(at)
            out_h, out_row, out_at, cut = [], [], [], []
            for i, text in enumerate(batch.column(3).to_pylist()):
                start = BEFORE - int(longest[i])
                for low in range(0, BEFORE + 1, _STEP):
                    high = min(low + _STEP - 1, BEFORE)
                    a, b = min(high, int(longest[i])), max(low, int(shortest[i]))
                    if a >= b:
                        inner = text[BEFORE - low - start : _WIDTH - high - start]
                        out_h.append(int.from_bytes(hashlib.blake2b(inner, digest_size=8, salt=int(h[i]).to_bytes(8, "big", signed=True) + bytes([low])).digest(), "big", signed=True))
                        out_row.append(i)
                        out_at.append(int(place[i]) << 10 | a << 5 | b)
                        cut.append(text[BEFORE - a - start : _WIDTH - b - start])
            yield pa.RecordBatch.from_arrays([pa.array(out_h, pa.int64()), pa.array(doc[np.array(out_row, np.int64)]), pa.array(out_at, pa.int64()), pa.array(cut, pa.binary())], names=["h", "doc", "at", "stretch"])

    pieces = materialize(stretches.select("h", "doc", "at", "stretch").mapInArrow(run, "h long, doc long, at long, stretch binary"))
    least = pieces.groupBy("h", "stretch").agg(F.min("doc").alias("least"))
    marked = materialize(pieces.join(least, ["h", "stretch"]))
    start, end = F.shiftright("at", 10) - F.shiftright("at", 5).bitwiseAND(31), F.shiftright("at", 10) - F.col("at").bitwiseAND(31) + SPAN
    runs = marked.where("doc > least").select("doc", start.alias("start"), end.alias("end"))
    return runs, marked.where("doc = least").select("h", "doc", "at", "stretch")


def repeated_runs(docs: DataFrame, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame | None]:
    """``(runs, grouped)``: runs ``(doc, start, end)`` to remove; the texts of each id, if ids repeat."""
    grouped, repeated = _grouped(docs, key, text)
    hashes = _anchors(grouped, False).groupBy("h").agg(F.min("doc").alias("a"), F.max("doc").alias("b")).where("a < b").select("h")
    hashes = materialize(hashes)
    # one row a key on the built side, so its partitions keep to their share
    shared = materialize(_anchors(grouped, True).join(hashes.hint("shuffle_hash"), "h"))
    release(hashes)
    classes = materialize(shared.groupBy("h", "c").agg(F.min("doc").alias("least"), F.max("doc").alias("most")))
    several = classes.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("least").alias("a"), F.max("least").alias("b")).where("n > 1 and a < b").select("h", (F.col("n") > HOT).alias("hot"))
    several = materialize(several)
    known = classes.join(several.withColumn("several", F.lit(True)), "h", "left").where("least < most or several").withColumnRenamed("h", "kh").withColumnRenamed("c", "kc")
    placed = shared.join(known.hint("shuffle_hash"), (F.col("h") == F.col("kh")) & (F.col("c") == F.col("kc"))).where("doc > least or several")
    placed = materialize(placed.select("h", "doc", "at", (F.col("doc") > F.col("least")).alias("later"), "hot"))
    release(shared, classes)
    whole = placed.where("later").select("doc", (F.shiftright("at", 10) - F.shiftright("at", 5).bitwiseAND(31)).alias("start"), (F.shiftright("at", 10) - F.col("at").bitwiseAND(31) + SPAN).alias("end"))
    firsts = placed.where("not later").select("h", "doc", "at")
    hot = several.where("hot").select("h")
    if hot.limit(1).count():
        cut = materialize(_stretches(grouped, firsts))
        hot = materialize(hot)
        runs, rest = _split_hot(cut.join(hot, "h"))
        whole = whole.unionByName(runs)
        stretches = cut.join(hot, "h", "left_anti").unionByName(rest)
    else:
        stretches = _stretches(grouped, firsts)
    sorted_runs = materialize(_sorted_runs(stretches))
    return whole.unionByName(sorted_runs), grouped if repeated else None


def _gaps(size: int, starts: np.ndarray, ends: np.ndarray) -> list[tuple[int, int]]:
    """Maximal removed runs of a text."""
    if not len(starts):
        return []
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], np.maximum.accumulate(ends[order])
    first = np.flatnonzero(np.concatenate([[True], starts[1:] > ends[:-1]]))
    return list(zip(starts[first].tolist(), ends[np.append(first[1:], len(ends)) - 1].tolist(), strict=True))


def _keep(text: bytes, gaps: list[tuple[int, int]]) -> bytes:
    if not gaps:
        return text
    edge = [0, *(x for g in gaps for x in g), len(text)]
    return b"".join(text[edge[i] : edge[i + 1]] for i in range(0, len(edge), 2))


def _cut(docs: DataFrame, key: str, text: str, digests: bool) -> DataFrame:
    runs, grouped = repeated_runs(docs, key, text)
    by_doc = runs.groupBy("doc").agg(F.collect_list("start").alias("starts"), F.collect_list("end").alias("ends"))
    index = "array_position(texts, coalesce(text, ''))"
    rows = docs.withColumnsRenamed({c: f"d_{c}" for c in docs.columns})
    rows = rows.withColumn("doc", F.col(f"d_{key}").cast("long")).withColumn("text", F.col(f"d_{text}"))
    joined = rows.drop(f"d_{text}").join(by_doc, "doc", "left")
    if grouped is not None:
        joined = joined.join(grouped, "doc", "left").withColumn("part", F.greatest(F.expr(index) - 1, F.lit(0))).drop("texts")
    else:
        joined = joined.withColumn("part", F.lit(0).cast("long"))
    others = [f"d_{c}" for c in docs.columns if c != text]
    picked = joined.select(*others, "text", "part", "starts", "ends")
    kinds = dict(docs.dtypes)
    schema = ", ".join(f"`d_{c}` {kinds[c]}" for c in docs.columns if c != text) + (", n_bytes long, n_removed long, n_spans long, kept_sha256 string" if digests else ", kept string")
    n = len(others)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            sizes, removed, spans, kept = [], [], [], []
            lists = [batch.column(n + 2), batch.column(n + 3)]
            for value, part, starts, ends in zip(batch.column(n), batch.column(n + 1).to_pylist(), *lists, strict=True):
                raw = value.as_py()
                data = (raw or "").encode()
                gaps = []
                if starts.is_valid:
                    a, b = starts.values.to_numpy() - part * _GAP, ends.values.to_numpy() - part * _GAP
                    mine = (a >= 0) & (a < _GAP)
                    gaps = _gaps(len(data), a[mine], b[mine])
                rest = _keep(data, gaps)
                sizes.append(len(data))
                removed.append(len(data) - len(rest))
                spans.append(len(gaps))
                # a cut may fall inside a character; its pieces go
                kept.append(hashlib.sha256(rest).hexdigest() if digests else raw if not gaps else rest.decode(errors="ignore"))
            out = [pa.array(x, pa.int64()) for x in (sizes, removed, spans)] if digests else []
            tail = ["n_bytes", "n_removed", "n_spans", "kept_sha256"] if digests else ["kept"]
            yield pa.RecordBatch.from_arrays([*(batch.column(j) for j in range(n)), *out, pa.array(kept, pa.string())], names=[*others, *tail])

    return picked.mapInArrow(run, schema)


def removal_digests(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: key, n_bytes, n_removed, n_spans, kept_sha256."""
    return _cut(docs.select(key, text), key, text, True).withColumnRenamed(f"d_{key}", key)


def without_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with repeated passages cut out of the text; rows and other columns stay."""
    out = _cut(docs, key, text, False)
    return out.select(*[F.col("kept").alias(c) if c == text else F.col(f"d_{c}").alias(c) for c in docs.columns])
