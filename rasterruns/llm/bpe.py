"""Byte-level BPE: encoding and decoding by rank files of public tokenizers.

Each match of the split pattern is merged on its own.  The ranks of the live
neighbouring pairs of a match stand at the leaves of a segment tree over byte
positions; the root names the smallest rank at its leftmost place.  A merge
changes three leaves, each in logarithmic time, so one match of n bytes takes
O(n log n) even when it is a whole document.

Defined results: a null text counts as empty and gives no ids; text that looks
like a special token is ordinary text; rows repeat as they come; other columns
are left alone.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from rasterruns.llm.common import sliced

#: Matches remembered by one task at most; the memory is emptied when it is full.
CACHE_PIECES = 400_000
_SHORT = 200


def read_ranks(path: str) -> dict[bytes, int]:
    """The rank file's tokens (its size is fixed by the tokenizer, some 50,000 lines)."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def merge_piece(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one match: always merge the lowest-ranked pair, the leftmost of equals."""
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    n = len(piece)
    if n < 2:
        return [ranks[piece[i : i + 1]] for i in range(n)]
    width = 1 << (n - 1).bit_length()
    none = 1 << 62
    get = ranks.get
    after = list(range(1, n + 1))  # start of the next live symbol
    before = list(range(-1, n - 1))
    tree = [none] * (2 * width)
    for i in range(n - 1):
        rank = get(piece[i : i + 2])
        if rank is not None:
            tree[width + i] = rank * width + i  # smaller rank first, then the leftmost
    for k in range(width - 1, 0, -1):
        a, b = tree[2 * k], tree[2 * k + 1]
        tree[k] = a if a < b else b

    def put(i: int, value: int) -> None:
        k = width + i
        tree[k] = value
        while k > 1:
            other = tree[k ^ 1]
            k >>= 1
            value = other if other < value else value
            if tree[k] == value:
                return
            tree[k] = value

    while tree[1] < none:
        i = tree[1] & (width - 1)
        j = after[i]
        end = after[j]
        after[i] = end
        put(j, none)
        if end < n:
            before[end] = i
            rank = get(piece[i : after[end]])
            put(i, none if rank is None else rank * width + i)
        else:
            put(i, none)
        h = before[i]
        if h >= 0:
            rank = get(piece[h:end])
            put(h, none if rank is None else rank * width + h)
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : after[i]]])
        i = after[i]
    return out


class Codec(dict):
    """Encodes and decodes whole texts; as a dict it maps a match to its packed ids."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.split = regex.compile(pattern).findall
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token

    def __missing__(self, piece: str) -> bytes:
        packed = np.array(merge_piece(piece.encode(), self.ranks), "<u4").tobytes()
        if len(piece) <= _SHORT:
            if len(self) >= CACHE_PIECES:
                self.clear()
            self[piece] = packed
        return packed

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.__getitem__, self.split(text or "")))

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(packed, "<u4").tolist()))


def _with_codec(df: DataFrame, rank_path: str, pattern: str):
    """Broadcast of the rank table: its size is that of the tokenizer's file, whatever the data."""
    return df.sparkSession.sparkContext.broadcast((read_ranks(rank_path), pattern))


def _lists(packed: list[bytes], sizes: np.ndarray) -> pa.ListArray:
    offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
    return pa.ListArray.from_arrays(offsets, pa.array(np.frombuffer(b"".join(packed), "<u4").astype(np.int32)))


def encode(df: DataFrame, rank_path: str, pattern: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(key, ids array<int>, n_tokens long)`` for every row of ``df``."""
    shared = _with_codec(df, rank_path, pattern)
    schema = T.StructType([T.StructField("key", df.schema[key].dataType), T.StructField("ids", T.ArrayType(T.IntegerType(), False)), T.StructField("n_tokens", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(*shared.value)
        for batch in sliced(batches):
            packed = [codec.encode(t) for t in batch.column(1).to_pylist()]
            sizes = np.array([len(p) // 4 for p in packed], np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), _lists(packed, sizes), pa.array(sizes)], names=["key", "ids", "n_tokens"])

    return df.select(df[key].alias("key"), df[text].alias("text")).mapInArrow(run, schema).withColumnRenamed("key", key)


def decode(df: DataFrame, rank_path: str, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """``(key, bytes binary)``: the bytes that the ids stand for; null ids give empty bytes."""
    shared = _with_codec(df, rank_path, "")
    schema = T.StructType([T.StructField("key", df.schema[key].dataType), T.StructField("bytes", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(*shared.value)
        for batch in sliced(batches):
            out = [codec.decode(np.array(x or [], "<u4").tobytes()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["key", "bytes"])

    return df.select(df[key].alias("key"), df[ids].alias("ids")).mapInArrow(run, schema).withColumnRenamed("key", key)


def round_trip_digests(df: DataFrame, rank_path: str, pattern: str, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """Encode, then decode what was encoded, keeping digests of both.

    Columns: key, n_tokens, ids_sha256, decoded_sha256, n_bytes (of the decoded
    text) and, if asked for, ids (array).
    """
    shared = _with_codec(df, rank_path, pattern)
    fields = [("n_tokens", T.LongType()), ("ids_sha256", T.StringType()), ("decoded_sha256", T.StringType()), ("n_bytes", T.LongType())]
    if with_ids:
        fields.append(("ids", T.ArrayType(T.IntegerType(), False)))
    schema = T.StructType([T.StructField("key", df.schema[key].dataType), *(T.StructField(*f) for f in fields)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(*shared.value)
        for batch in sliced(batches):
            packs, ids, back, size = [], [], [], []
            for value in batch.column(1):
                packed = codec.encode(value.as_py())
                plain = codec.decode(packed)
                packs.append(packed if with_ids else b"")
                ids.append((len(packed) // 4, hashlib.sha256(packed).hexdigest()))
                back.append(hashlib.sha256(plain).hexdigest())
                size.append(len(plain))
            n = np.array([x[0] for x in ids], np.int64)
            columns = [batch.column(0), pa.array(n), pa.array([x[1] for x in ids], pa.string()), pa.array(back, pa.string()), pa.array(size, pa.int64())]
            if with_ids:
                columns.append(_lists(packs, n))
            yield pa.RecordBatch.from_arrays(columns, names=["key", *(f[0] for f in fields)])

    return df.select(df[key].alias("key"), df[text].alias("text")).mapInArrow(run, schema).withColumnRenamed("key", key)
