"""Near-duplicate documents by MinHash banding, verified on full shingle sets.

A document's set holds its distinct shingles of ``words`` words (a shorter
document is one shingle; a document without words has none and links with
nothing).  Equal sets are one node from the start.

1. Many universal hash minima of a node are cut into bands; nodes that agree on
   a band share a bucket.
2. Every bucket member is compared with one centre of its bucket, first by the
   share of equal minima, then on full sets.
3. Buckets whose members still lie in several components get a better centre
   (the member that shares most buckets), and then all remaining pairs of
   members from different components are compared: small buckets by a self-join
   on the bucket, large ones in blocks of full sets, whose tasks return just the
   links that join components.  So a pair is skipped only
   if its members are connected already.
4. Components by alternating large-star and small-star; the smallest id of a
   component is kept.

With 32 bands of 5 minima a pair at 85 % shares no bucket once in 10^8, at 80 %
once in 3 * 10^5 (and is then usually joined through a third document).  The
test by equal minima loses a pair at 85 % once in 10^9, at 80 % once in 7 * 10^7,
so both together lose some 8 in 10^9 and 3 in 10^6.

Defined results: rows with the same id are one document, linked if any of its
texts is; rows without an id link with nothing and are kept; repeated rows
repeat in the result; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rasterruns.llm.common import materialize, sliced
from rasterruns.llm.components import connected_components

BANDS, ROWS = 32, 5
#: A pair whose estimate falls short by more than this isn't read in full; so wide that it loses less than the bands do.
MARGIN = 0.19
#: Members of a bucket up to which its pairs come from a self-join, and bytes of sets in a block beyond.
SMALL_BUCKET = 48
BLOCK_BYTES = 8 << 20
#: Words remembered by one task at most.
CACHE_WORDS = 500_000
_U = np.uint64


def _mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def _odd(n: int, seed: int, kind) -> np.ndarray:
    """Odd multipliers by rule from the seed."""
    with np.errstate(over="ignore"):
        return (_mix(np.arange(1, n + 1, dtype=_U) + _U(seed * 1_000_003)) >> _U(64 - 8 * np.dtype(kind).itemsize)).astype(kind) | kind(1)


class Shingler(dict):
    """Maps a word to 64 bits; ``sets`` gives sorted distinct shingle hashes of texts."""

    def __init__(self, words: int):
        self.words = words
        self.weights = _odd(words, 1, _U)

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= CACHE_WORDS:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value

    def shingles(self, text: str | None) -> np.ndarray:
        words = (text or "").encode().lower().split()  # bytes: only A-Z change, only ASCII space splits
        n = len(words)
        if not n:
            return np.zeros(0, _U)
        ids = np.fromiter(map(self.__getitem__, words), _U, n)
        k = min(self.words, n)
        with np.errstate(over="ignore"):
            h = np.full(n - k + 1, _U(k))
            for j in range(k):
                h = h + ids[j : n - k + 1 + j] * self.weights[j]
        return np.unique(_mix(h))


def signature(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least value of each hash ``a x + b`` (32 bits) over the set."""
    x = (shingles >> _U(32)).astype(np.uint32)
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    with np.errstate(over="ignore"):
        for i in range(0, len(x), 1024):
            y = a[:, None] * x[None, i : i + 1024]
            y += b[:, None]
            np.minimum(out, (y ^ (y >> np.uint32(15))).min(axis=1), out=out)
    return out


def _profiles(docs: DataFrame, words: int) -> DataFrame:
    """``(doc, n_shingles, sid, sketch, bands)`` per row; sid: 128-bit name of the set, null if empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        shingler = Shingler(words)
        n = BANDS * ROWS
        a, b = _odd(n, 2, np.uint32), _odd(n, 3, np.uint32)
        fold, tag = _odd(ROWS, 4, _U), _odd(BANDS, 5, _U)
        for batch in sliced(batches):
            sizes, sids, sketches, signatures = [], [], [], []
            for t in batch.column(1):
                s = shingler.shingles(t.as_py())
                sizes.append(len(s))
                if not len(s):
                    sids.append(None)
                    sketches.append(None)
                    continue
                sids.append(xxhash.xxh3_128_digest(s.tobytes()))
                m = signature(s, a, b)
                signatures.append(m)
                sketches.append((m & np.uint32(255)).astype(np.uint8).tobytes())
            full = np.array([x is not None for x in sids], bool)
            with np.errstate(over="ignore"):
                m = np.array(signatures, np.uint32).reshape(-1, BANDS, ROWS).astype(_U)
                keys = _mix((m * fold).sum(axis=2, dtype=_U) + tag).view(np.int64)
            offsets = np.concatenate([[0], np.cumsum(full * BANDS)]).astype(np.int32)
            bands = pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(sids, pa.binary()), pa.array(sketches, pa.binary()), bands], names=["doc", "n_shingles", "sid", "sketch", "bands"])

    return docs.mapInArrow(run, "doc long, n_shingles long, sid binary, sketch binary, bands array<long>")


def _likely(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Pairs ``(a, b)`` whose signatures agree nearly enough."""
    least = percent / 100 - MARGIN
    sketch = nodes.select("node", "sketch")
    both = pairs.join(sketch.withColumnsRenamed({"node": "a", "sketch": "sa"}), "a").join(sketch.withColumnsRenamed({"node": "b", "sketch": "sb"}), "b").select("a", "b", "sa", "sb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (np.frombuffer(b"".join(batch.column(j).to_pylist()), np.uint8).reshape(-1, BANDS * ROWS) for j in (2, 3))
            good = pa.array((x == y).mean(axis=1) >= least)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(good), batch.column(1).filter(good)], names=["a", "b"])

    return both.mapInArrow(run, "a long, b long")


def _full_sets(docs: DataFrame, nodes: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """``(node, shingles)`` of the wanted nodes, from the text of each node's first document."""
    rows = docs.join(nodes.join(wanted, "node").select("node", "rep", "sid"), docs["doc"] == F.col("rep")).select("node", "sid", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        shingler = Shingler(words)
        for batch in sliced(batches):
            ids, sets = [], []
            for node, sid, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                packed = shingler.shingles(text.as_py()).tobytes()
                if xxhash.xxh3_128_digest(packed) == sid:  # an id may stand on several texts
                    ids.append(node)
                    sets.append(packed)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(sets, pa.binary())], names=["node", "shingles"])

    return rows.mapInArrow(run, "node long, shingles binary")


def _confirmed(pairs: DataFrame, docs: DataFrame, nodes: DataFrame, words: int, percent: int) -> DataFrame:
    """``(u, v)``: the pairs with 100 * intersection >= percent * union on their full sets."""
    likely = materialize(_likely(pairs, nodes, percent))
    wanted = likely.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    full = materialize(_full_sets(docs, nodes, wanted, words).dropDuplicates(["node"]))
    both = likely.join(full.withColumnsRenamed({"node": "a", "shingles": "xa"}), "a").join(full.withColumnsRenamed({"node": "b", "shingles": "xb"}), "b").select("a", "b", "xa", "xb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), _U), np.frombuffer(y.as_buffer(), _U)
                if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    good.append(False)
                    continue
                both = np.concatenate([x, y])
                both.sort(kind="stable")  # merges the two sorted runs
                same = int((both[1:] == both[:-1]).sum())
                good.append(100 * same >= percent * (len(x) + len(y) - same))
            good = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(good), batch.column(1).filter(good)], names=["u", "v"])

    return both.mapInArrow(run, "u long, v long")


class _Union(dict):
    """Components that a task has joined so far; a missing label stands for itself."""

    def root(self, x: int) -> int:
        while x in self:
            x = self[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        if x != y:
            self[max(x, y)] = min(x, y)
        return x != y


def _block_links(band: int, node: np.ndarray, comp: np.ndarray, left: np.ndarray, right: np.ndarray, same: bool, bands: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links between components, enough to join them: pairs of the two sides whose first common band is this one."""
    size = np.array([len(x) for x in sets], np.int64)
    _, flat = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.cumsum(size)
    mark = np.zeros(int(flat.max()) + 1, bool)
    values, counts = np.unique(comp, return_counts=True)
    main = comp == values[counts.argmax()]
    joined, out = _Union(), []
    for p in np.flatnonzero(~main).tolist():
        q = np.arange(len(node)) if same else right if left[p] else left
        q = np.flatnonzero(q) if q.dtype == bool else q
        q = q[(comp[q] != comp[p]) & (main[q] | (node[q] > node[p]))]
        q = q[(100 * np.minimum(size[q], size[p]) >= percent * np.maximum(size[q], size[p]))]
        q = q[bands[p][(bands[q] == bands[p]).argmax(axis=1)] == band] if len(q) else q
        if not len(q):
            continue
        mine = flat[ends[p] - size[p] : ends[p]]
        mark[mine] = True
        at = np.repeat(ends[q] - np.cumsum(size[q]), size[q]) + np.arange(size[q].sum())
        both = np.add.reduceat(mark[flat[at]].astype(np.int64), np.cumsum(size[q]) - size[q])
        mark[mine] = False
        for k in q[100 * both >= percent * (size[q] + size[p] - both)].tolist():
            if joined.join(int(comp[p]), int(comp[k])):
                out.append((int(node[p]), int(node[k])))
    return out


def _blocked_links(members: DataFrame, docs: DataFrame, nodes: DataFrame, words: int, percent: int) -> DataFrame:
    """``(u, v)``: links that join the components of large buckets ``(band, node, comp)``.

    A bucket is dealt into blocks by the bytes of its sets; a task compares two
    blocks on full sets, so its memory is bounded, and returns at most one link
    a component.
    """
    full = materialize(_full_sets(docs, nodes, members.select("node").distinct(), words).dropDuplicates(["node"]))
    rows = members.join(full, "node")
    sizes = rows.groupBy("band").agg(F.ceil(F.sum(F.length("shingles")) / BLOCK_BYTES).alias("blocks"))
    rows = rows.join(sizes, "band").join(nodes.select("node", "bands"), "node")
    rows = rows.withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("band", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "mine", "node", "comp", "shingles", "bands")

    def run(key, table):
        band, i, j = (k.as_py() for k in key)
        mine, node, comp = (table.column(c).to_numpy() for c in ("mine", "node", "comp"))
        bands = table.column("bands").combine_chunks().flatten().to_numpy().reshape(-1, BANDS)
        sets = [np.frombuffer(x.as_buffer(), _U) for x in table.column("shingles")]
        links = _block_links(band, node, comp, mine == i, mine == j, i == j, bands, sets, percent)
        return pa.table({"u": pa.array([x for x, _ in links], pa.int64()), "v": pa.array([y for _, y in links], pa.int64())})

    return rows.groupBy("band", "i", "j").applyInArrow(run, "u long, v long")


def near_duplicates(documents: DataFrame, words: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``documents``: key, n_shingles, component_id (smallest id reachable), kept."""
    docs = documents.select(documents[key].cast("long").alias("doc"), documents[text].alias("text"))
    rows = materialize(_profiles(docs, words))
    linked = rows.where("doc is not null and sid is not null")
    nodes = linked.groupBy("sid").agg(F.min("doc").alias("rep"), F.first("sketch").alias("sketch"), F.first("bands").alias("bands"))
    nodes = materialize(nodes.withColumn("node", F.monotonically_increasing_id()))
    member = linked.select("doc", "sid").distinct().join(nodes.select("sid", "node"), "sid").select("doc", "node")
    several = member.groupBy("doc").agg(F.min("node").alias("u"), F.max("node").alias("w")).where("u < w")
    links = materialize(member.join(several, "doc").where("node > u").select("u", F.col("node").alias("v")))

    buckets = materialize(nodes.select("node", F.explode("bands").alias("band")))
    centres = buckets.groupBy("band").agg(F.min("node").alias("centre"), F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = materialize(buckets.join(centres, "band"))  # only buckets with company
    tested = materialize(shared.where("node > centre").select(F.col("centre").alias("a"), F.col("node").alias("b")).distinct())
    links = links.union(materialize(_confirmed(tested, docs, nodes, words, percent)))
    component = materialize(connected_components(links))

    def open_buckets(component: DataFrame) -> DataFrame:
        """Members of the buckets that still hold several components."""
        placed = shared.select("band", "n", "node").join(component, "node", "left").withColumn("comp", F.coalesce("component", "node"))
        mixed = placed.groupBy("band").agg(F.min("comp").alias("c1"), F.max("comp").alias("c2")).where("c1 < c2").select("band")
        return placed.select("band", "n", "node", "comp").join(mixed, "band")

    def fresh(pairs: DataFrame) -> DataFrame:
        return pairs.distinct().join(tested, ["a", "b"], "left_anti")

    rest = materialize(open_buckets(component))
    if rest.limit(1).count():
        reach = rest.groupBy("node").agg(F.sum("n").alias("reach"))
        best = rest.join(reach, "node").groupBy("band").agg(F.max_by(F.struct("node", "comp"), F.struct("reach", "node")).alias("best"))
        stars = rest.join(best, "band").where("comp <> best.comp").select(F.least("node", "best.node").alias("a"), F.greatest("node", "best.node").alias("b"))
        stars = materialize(fresh(stars))
        tested = tested.union(stars)
        links = links.union(materialize(_confirmed(stars, docs, nodes, words, percent)))
        component = materialize(connected_components(links))
        rest = materialize(open_buckets(component))
        small = rest.where(F.col("n") <= SMALL_BUCKET)
        one, two = small.select("band", F.col("node").alias("a"), F.col("comp").alias("ca")), small.select("band", F.col("node").alias("b"), F.col("comp").alias("cb"))
        pairs = one.join(two, "band").where("a < b and ca <> cb").select("a", "b")
        last = _confirmed(materialize(fresh(pairs)), docs, nodes, words, percent)
        last = materialize(last.union(_blocked_links(rest.where(F.col("n") > SMALL_BUCKET).select("band", "node", "comp"), docs, nodes, words, percent)))
        if last.limit(1).count():
            links = links.union(last)
            component = materialize(connected_components(links))

    of_doc = member.join(component, "node", "left").select("doc", F.coalesce("component", "node").alias("comp"))
    least = of_doc.groupBy("comp").agg(F.min("doc").alias("component_id"))
    answer = of_doc.join(least, "comp").select(F.col("doc").alias("d"), "component_id").distinct()
    out = rows.select("doc", "n_shingles").join(answer, F.col("doc") == F.col("d"), "left")
    out = out.select(F.col("doc").alias(key), "n_shingles", F.coalesce("component_id", "doc").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col(key) == F.col("component_id"), F.lit(True)))


def without_near_duplicates(documents: DataFrame, words: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``documents`` less those that are not the first of their component; columns stay."""
    gone = near_duplicates(documents, words, percent, key, text).where("not kept").select(F.col(key).alias("gone")).distinct()
    rows = documents.toDF(*[f"c{i}" for i in range(len(documents.columns))])
    rest = rows.join(gone, F.col(f"c{documents.columns.index(key)}").cast("long") == F.col("gone"), "left_anti")
    return rest.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(documents.columns)])
