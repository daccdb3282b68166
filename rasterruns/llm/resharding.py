"""Resharding by minimum-cost flow: reach new shard capacities while moving the fewest bytes.

Shards take an equal count of rows, at most one apart, so an old shard with
more than that sheds its smallest rows.  A count of rows by exact size finds the
size at which each old shard's surplus ends, and its rows fall into three
blocks: below, at and above that size.  A block's rows may stay (cost 0) or move
(cost: the block's mean bytes a row, exact where it matters, as the block at the
size has one size only).  The flow is solved on the block table, three rows an
old shard whatever the data; it also decides which shards take one row more.
A transfer names a stretch of ranks of one block, so each row finds its shard
by a join with a small table.  ``lay_out`` stores documents as folders
``shard=N``; ``reshard_files`` places the stored rows, replaces the files of the
shards that give or take rows and leaves the others alone.

Defined results: null text has 0 bytes; equal texts, repeated ids and null ids
are rows like any other and are dealt out as such, so a text that makes up a
third of all rows spreads evenly; an empty table gives no rows.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rasterruns.llm.common import materialize, release, salted_rank
from rasterruns.runtime import _delete, released_shuffles

#: Bytes that every document takes besides its text.
OVERHEAD = 16
SALTS = 64
#: The codec of stored shards.
CODEC = "zstd"


class FlowNetwork:
    """Successive shortest paths with potentials; all costs are non-negative."""

    def __init__(self, nodes: int):
        self.arcs: list[list[int]] = [[] for _ in range(nodes)]
        self.head: list[int] = []
        self.room: list[int] = []
        self.cost: list[float] = []

    def arc(self, a: int, b: int, room: int, cost: float) -> int:
        for start, end, r, c in ((a, b, room, cost), (b, a, 0, -cost)):
            self.arcs[start].append(len(self.head))
            self.head.append(end)
            self.room.append(r)
            self.cost.append(c)
        return len(self.head) - 2

    def solve(self, source: int, sink: int) -> tuple[int, float]:
        """Send all the flow there is; returns its amount and cost."""
        n, price, sent, paid = len(self.arcs), [0.0] * len(self.arcs), 0, 0.0
        while True:
            far, via = [float("inf")] * n, [-1] * n
            far[source] = 0.0
            heap = [(0.0, source)]
            while heap:
                d, a = heapq.heappop(heap)
                if d > far[a]:
                    continue
                for e in self.arcs[a]:
                    if self.room[e] and (step := d + max(0.0, self.cost[e] + price[a] - price[self.head[e]])) < far[self.head[e]] - 1e-9:
                        far[self.head[e]], via[self.head[e]] = step, e
                        heapq.heappush(heap, (step, self.head[e]))
            if via[sink] < 0:
                return sent, paid
            reach = far[sink]
            price = [p + min(f, reach) for p, f in zip(price, far, strict=True)]
            path, b = [], sink
            while b != source:
                path.append(via[b])
                b = self.head[via[b] ^ 1]
            push = min(self.room[e] for e in path)
            for e in path:
                self.room[e] -= push
                self.room[e ^ 1] += push
                paid += push * self.cost[e]
            sent += push


def plan_transfers(blocks: list[tuple[int, int, int, int]], shards: int) -> list[tuple[int, int, int, int, int]]:
    """``blocks`` of (shard, block, rows, bytes) -> (shard, block, from rank, to rank, new shard).

    Every new shard gets rows // shards rows or one more; who gets one more is
    part of the flow.  Rows of a block are told apart by rank only, so a
    block's stretch is [from, to).
    """
    total = sum(b[2] for b in blocks)
    if not total:
        return []
    base, extra = divmod(total, shards)
    first = len(blocks)
    hub, spare, source, sink = first + shards, first + shards + 1, first + shards + 2, first + shards + 3
    net = FlowNetwork(sink + 1)
    stay, leave = {}, []
    for i, (shard, _, rows, size) in enumerate(blocks):
        net.arc(source, i, rows, 0.0)
        if shard < shards:
            stay[i] = net.arc(i, first + shard, rows, 0.0)
        leave.append(net.arc(i, hub, rows, size / rows))
    arrive = []
    for j in range(shards):
        arrive.append(net.arc(hub, first + j, total, 0.0))
        net.arc(first + j, sink, base, 0.0)
        net.arc(first + j, spare, 1, 0.0)
    net.arc(spare, sink, extra, 0.0)
    sent, _ = net.solve(source, sink)
    if sent != total:
        raise RuntimeError("the flow doesn't place all rows")
    free = [[j, net.room[e ^ 1]] for j, e in enumerate(arrive) if net.room[e ^ 1]]
    out = []
    for i, (shard, kind, rows, _) in enumerate(blocks):
        at = net.room[stay[i] ^ 1] if i in stay else 0
        if at:
            out.append((shard, kind, 0, at, shard))
        left = net.room[leave[i] ^ 1]
        while left:
            n = min(left, free[-1][1])
            out.append((shard, kind, at, at + n, free[-1][0]))
            at, left = at + n, left - n
            free[-1][1] -= n
            if not free[-1][1]:
                free.pop()
        if at != rows:
            raise RuntimeError("a block isn't placed whole")
    return out


def _surplus_ends(rows: DataFrame, shards: int) -> DataFrame:
    """``(old_shard, edge)``: the size of the last of an old shard's smallest rows that are too many.

    Rows are counted by exact size before they are sorted, so equal sizes are one row here.
    """
    by_size = rows.groupBy("old_shard", "size").agg(F.count(F.lit(1)).alias("n"))
    line = Window.partitionBy("old_shard").orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    all_ = rows.groupBy("old_shard").agg(F.count(F.lit(1)).alias("rows"))
    total = sum(r.rows for r in all_.collect())  # one row an old shard
    reach = by_size.withColumn("upto", F.sum("n").over(line)).join(F.broadcast(all_), "old_shard")
    surplus = F.col("rows") - total // shards
    return reach.where((surplus > 0) & (F.col("upto") >= surplus)).groupBy("old_shard").agg(F.min("size").alias("edge"))


def _size(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + OVERHEAD


def _crc(text: Column) -> Column:
    return F.crc32(F.coalesce(text, F.lit("")).cast("binary"))


def _salt(key: str) -> Column:
    return F.pmod(F.xxhash64(key, F.lit(1)), F.lit(SALTS))


def _ranked(rows: DataFrame, shards: int) -> tuple[DataFrame, list[tuple[int, int, int, int, int]]]:
    """``rows(key, size, text_crc32, old_shard, ...)`` with kind and rank in its block, and the transfers of the blocks."""
    edges = F.broadcast(_surplus_ends(rows, shards))  # one row an old shard
    rows = rows.join(edges, "old_shard", "left").withColumn("kind", F.when(F.col("size") < F.col("edge"), 0).when(F.col("size") == F.col("edge"), 1).otherwise(2)).drop("edge")
    blocks = [tuple(r) for r in rows.groupBy("old_shard", "kind").agg(F.count(F.lit(1)), F.sum("size")).orderBy("old_shard", "kind").collect()]
    return salted_rank(rows, ["old_shard", "kind"], [F.col("key"), F.col("text_crc32")], _salt("key"), "_rank", few=True), plan_transfers(blocks, shards)


def _placed(ranked: DataFrame, transfers: list[tuple[int, int, int, int, int]]) -> DataFrame:
    """Add shard and slot: the transfers into a shard stand one after the other, so its slots are gapless from 0."""
    filled: dict[int, int] = {}
    table = []
    for t in transfers:
        table.append((*t, filled.get(t[4], 0)))
        filled[t[4]] = table[-1][5] + t[3] - t[2]
    schema = T.StructType([T.StructField(n, t()) for n, t in (("_s", T.IntegerType), ("_c", T.IntegerType), ("_from", T.LongType), ("_to", T.LongType), ("shard", T.IntegerType), ("_base", T.LongType))])
    moves = F.broadcast(ranked.sparkSession.createDataFrame(table, schema))  # at most blocks + shards rows, a bound free of the data
    rank = F.col("_rank")
    placed = ranked.join(moves, (F.col("old_shard") == F.col("_s")) & (F.col("kind") == F.col("_c")) & (rank >= F.col("_from")) & (rank < F.col("_to")))
    return placed.withColumn("slot", F.col("_base") + rank - F.col("_from")).drop("kind", "_rank", "_s", "_c", "_from", "_to", "_base")


def reshard(docs: DataFrame, old_shards: int = 32, shards: int = 40, key: str = "doc_id", text: str = "text", old: str | None = None) -> DataFrame:
    """Place all rows of ``docs`` into ``shards`` shards of equal row counts (law ``rows``).

    ``old`` names the column of the present shard; without it the rows are
    taken as laid out by a hash of the key over ``old_shards``.  Columns: key,
    size, text_crc32, law, shard, slot (gapless from 0 in a shard),
    grown_shard (null under this law), old_shard, moved.
    """
    present = docs[old] if old else F.pmod(F.xxhash64(docs[key]), F.lit(old_shards))
    rows = materialize(docs.select(docs[key].alias("key"), _size(docs[text]).alias("size"), _crc(docs[text]).alias("text_crc32"), present.cast("int").alias("old_shard")))
    placed = _placed(*_ranked(rows, shards))
    return placed.select(F.col("key").alias(key), "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "old_shard", (F.col("shard") != F.col("old_shard")).alias("moved"))


def _write(rows: DataFrame, path: str) -> None:
    """Replace the folders ``shard=N`` of the shards in ``rows``; the shuffle files are released when the job ends."""
    with released_shuffles(rows.sparkSession):
        rows.write.option("partitionOverwriteMode", "dynamic").option("compression", CODEC).mode("overwrite").partitionBy("shard").parquet(path)


def lay_out(docs: DataFrame, path: str, shards: int = 32, key: str = "doc_id", text: str = "text") -> None:
    """Store ``docs`` as folders ``shard=N`` by a hash of the key, with a ``slot`` that is gapless from 0 in a shard."""
    if clash := {"shard", "slot"} & set(docs.columns):
        raise ValueError(f"columns {sorted(clash)} are taken by the layout")
    rows = docs.withColumn("shard", F.pmod(F.xxhash64(key), F.lit(shards)).cast("int"))
    _write(salted_rank(rows, ["shard"], [F.col(key), _crc(F.col(text))], _salt(key), "slot", few=True), path)


def stored(spark: SparkSession, path: str, schema: T.StructType | None = None) -> DataFrame:
    """The rows of a folder of shards; ``schema`` reads a folder that may hold no row."""
    return (spark.read.schema(schema) if schema else spark.read).parquet(path)


def reshard_files(docs: DataFrame, path: str, shards: int = 40, key: str = "doc_id", text: str = "text") -> None:
    """Bring the folders under ``path``, whose rows (with shard and slot) are ``docs``, to ``shards`` shards of equal row counts.

    Rows travel once, with their text, from their old shard's folder to the
    new one; no key need be unique.  Shards that neither give nor take rows keep
    their files; of the others the folders are replaced when all new files are
    written, or deleted when no row is left.
    """
    own = [c for c in docs.columns if c not in ("shard", "slot")]
    rows = docs.select(F.struct(*own).alias("row"), F.col(key).alias("key"), _size(F.col(text)).alias("size"), _crc(F.col(text)).alias("text_crc32"), F.col("shard").alias("old_shard"))
    ranked, transfers = _ranked(rows, shards)
    before, after = {t[0] for t in transfers}, {t[4] for t in transfers}
    changed = {s for t in transfers if t[0] != t[4] for s in (t[0], t[4])}
    if not changed:
        return
    placed = _placed(ranked, transfers).where(F.col("shard").isin(sorted(changed & after)))
    _write(placed.select("row.*", "slot", "shard"), path)
    for shard in sorted(before - after):
        _delete(docs.sparkSession, f"{path}/shard={shard}")


def digests(docs: DataFrame, path: str, old_shards: int = 32, shards: int = 40, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Lay ``docs`` out over ``old_shards``, reshard the files, and read each row's place, size and checksum back from them.

    Columns as ``reshard`` gives them.
    """
    spark = docs.sparkSession
    lay_out(docs, path, old_shards, key, text)
    schema = T.StructType([T.StructField(f.name, f.dataType) for f in docs.schema] + [T.StructField("slot", T.LongType()), T.StructField("shard", T.IntegerType())])
    reshard_files(stored(spark, path, schema), path, shards, key, text)
    got = stored(spark, path, schema)
    old = F.pmod(F.xxhash64(key), F.lit(old_shards)).cast("int")
    return got.select(key, _size(F.col(text)).alias("size"), _crc(F.col(text)).alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), old.alias("old_shard"), (F.col("shard") != old).alias("moved"))


def rewrite_affected(docs: DataFrame, placement: DataFrame, path: str, key: str = "doc_id") -> None:
    """Bring the folders ``shard=N`` under ``path``, which hold ``docs`` by old shard, to the placement.

    Shards that neither give nor take rows keep their files; of the others the
    folders are replaced, or deleted when no row is left.  The rows are cut
    first, so ``docs`` may be read from ``path`` itself.  The key must be
    unique here, as files are found by it.
    """
    spark = docs.sparkSession
    changed = placement.where("moved").select(F.explode(F.array("shard", "old_shard")).alias("shard")).distinct()
    target = placement.join(F.broadcast(changed), "shard").select(F.col(key).alias("_k"), "shard", "slot")
    rows = docs.drop("shard", "slot").join(target, docs[key].eqNullSafe(F.col("_k"))).drop("_k")
    rows = materialize(rows.repartition("shard", F.pmod(F.col("slot"), F.lit(16))).sortWithinPartitions("shard", "slot"))
    filled = {r.shard for r in rows.select("shard").distinct().collect()}  # at most one row a shard
    empty = [r.shard for r in changed.collect() if r.shard not in filled]
    rows.write.option("partitionOverwriteMode", "dynamic").mode("overwrite").partitionBy("shard").parquet(path)
    for shard in empty:
        _delete(spark, f"{path}/shard={shard}")
    release(rows)
