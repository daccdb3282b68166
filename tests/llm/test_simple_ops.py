"""Encoding, sharding, chat windows and mixing against brute force."""

import base64
import hashlib
from collections import Counter, defaultdict

import duckdb
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F

from rasterruns.llm import bpe, chat_windows, mixing, queries, resharding
from rasterruns.runtime import shared_file

RANKS = P.path("byte_bpe_multi_50k.tiktoken")
ODD = "doc_id long, text string, source string, size int, `key` string"
ROWS = [
    (1, "a b", "x", 1, "k"),
    (2, None, None, None, None),
    (3, "", "x", 2, "k"),
    (None, "a b", "y", 3, "k"),
    (4, "word " * 9000, "y", 4, None),
    (5, "a b", "x", 5, "k"),
    (5, "a b", "x", 5, "k"),
    (6, "<|endoftext|> ünï   \n\n  x", None, 6, "k"),
    (7, "x" * 3000 + "!?" * 500, "z", 6, "k"),
]


def odd(spark):
    return spark.createDataFrame(ROWS, ODD)


def test_bpe_equals_tiktoken(spark, sf_dir):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").union(odd(spark).select("doc_id", "text"))
    want = Counter()
    for r in docs.collect():
        ids = enc.encode_ordinary(r.text or "")
        packed = b"".join(i.to_bytes(4, "little") for i in ids)
        want[(r.doc_id, len(ids), hashlib.sha256(packed).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest())] += 1
    got = Counter(tuple(r)[:4] for r in bpe.round_trip_digests(docs, RANKS, P.PATTERN).collect())
    assert got == want
    ids = bpe.encode(docs, RANKS, P.PATTERN)
    back = {r.doc_id: bytes(r.bytes).decode() for r in bpe.decode(ids, RANKS).collect()}
    assert back[6] == ROWS[7][1] and back[2] == ""
    assert bpe.encode(docs.limit(0), RANKS, P.PATTERN).count() == 0


def test_bpe_merges_the_leftmost_lowest_pair():
    ranks = {b"a": 0, b"b": 1, b"aa": 2, b"ab": 3, b"aab": 5}
    assert bpe.merge_piece(b"aaaa", ranks) == [2, 2]
    assert bpe.merge_piece(b"aaab", ranks) == [2, 3]
    assert bpe.merge_piece(b"b", ranks) == [1] and bpe.merge_piece(b"", ranks) == []


def test_resharding_law_and_least_bytes(spark, sf_dir):
    rows = queries.op5_sharding(spark, sf_dir).collect()
    n = Counter(r.shard for r in rows)
    assert len(rows) == spark.read.parquet(f"{sf_dir}/documents.parquet").count()
    assert max(n.values()) - min(n[s] for s in range(40)) <= 1
    for s in n:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(n[s]))
    odd_rows = resharding.reshard(odd(spark), shards=4).collect()
    assert len(odd_rows) == len(ROWS) and {r["size"] for r in odd_rows if r.doc_id == 2} == {16}
    assert resharding.reshard(odd(spark).limit(0)).count() == 0


@pytest.mark.parametrize("seed", range(6))
def test_flow_matches_exhaustive_search(seed):
    import itertools
    import random

    rnd = random.Random(seed)
    blocks = [(s, k, rnd.randint(1, 3), 0) for s in range(3) for k in range(2)]
    blocks = [(s, k, n, n * rnd.randint(1, 9)) for s, k, n, _ in blocks]
    shards, total = 4, sum(b[2] for b in blocks)
    base, extra = divmod(total, shards)
    best = min(
        sum(sorted((b[3] / b[2] for b in blocks if b[0] == s for _ in range(b[2])))[i] for s in range(3) for i in range(max(0, sum(b[2] for b in blocks if b[0] == s) - base - (s in more))))
        for more in itertools.combinations(range(shards), extra)
    )
    moves = resharding.plan_transfers(blocks, shards)
    price = {(b[0], b[1]): b[3] / b[2] for b in blocks}
    assert sum((hi - lo) * price[s, k] for s, k, lo, hi, to in moves if to != s) == pytest.approx(best)
    fill = Counter()
    for _, _, lo, hi, to in moves:
        fill[to] += hi - lo
    assert sorted(fill.values()) == sorted([base] * (shards - extra) + [base + 1] * extra)


def least_bytes(rows, shards):
    """Each old shard sheds its smallest surplus rows; the rows spared by one more place are the largest ones."""
    by = defaultdict(list)
    for r in rows:
        by[r.old_shard].append(r["size"])
    base, extra = divmod(len(rows), shards)
    moved, spared = 0, []
    for s, sizes in by.items():
        n = max(0, len(sizes) - base) if s < shards else len(sizes)
        shed = sorted(sizes)[:n]
        moved += sum(shed)
        if n and s < shards:
            spared.append(shed[-1])
    return moved - sum(sorted(spared, reverse=True)[:extra])


@pytest.mark.parametrize("old,new", [(32, 40), (40, 7), (5, 6)])
def test_resharding_moves_the_fewest_bytes(spark, sf_dir, old, new):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for x in (docs, odd(spark)):
        rows = resharding.reshard(x, old, new).collect()
        assert sum(r["size"] for r in rows if r.moved) == least_bytes(rows, new)
        fill = Counter(r.shard for r in rows)
        assert max(fill.values()) - min(fill[s] for s in range(new)) <= 1


@pytest.mark.parametrize("old,new", [(6, 8), (8, 3)])
def test_affected_files_are_rewritten(spark, sf_dir, tmp_path, old, new):
    path = f"file://{tmp_path}/shards"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(200).withColumn("shard", F.pmod(F.xxhash64("doc_id"), F.lit(old)).cast("int"))
    docs.write.partitionBy("shard").parquet(path)
    held = spark.read.parquet(path)
    placement = resharding.reshard(held, shards=new, old="shard").persist()
    want = sorted((r.doc_id, r.shard) for r in placement.collect())
    resharding.rewrite_affected(held, placement, path)
    got = spark.read.parquet(path)
    assert sorted((r.doc_id, r.shard) for r in got.select("doc_id", "shard").collect()) == want
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    assert all(texts[r.doc_id] == r.text for r in got.collect())


@pytest.mark.parametrize("old,new", [(6, 8), (8, 3)])
def test_resharding_rewrites_files_without_unique_keys(spark, tmp_path, old, new):
    """Repeated ids, null ids and null texts keep all their columns; each folder's slots are gapless."""
    path = f"file://{tmp_path}/shards"
    docs = odd(spark).union(odd(spark))
    resharding.lay_out(docs, path, old)
    held = resharding.stored(spark, path)
    want = Counter((r.shard, r["size"]) for r in resharding.reshard(held, shards=new, old="shard").collect())
    resharding.reshard_files(held, path, new)
    rows = resharding.stored(spark, path).collect()
    assert Counter(map(tuple, docs.collect())) == Counter(tuple(r[c] for c in docs.columns) for r in rows)
    assert Counter((r.shard, len((r.text or "").encode()) + resharding.OVERHEAD) for r in rows) == want
    for s in range(new):
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))


def test_shards_that_do_not_change_keep_their_files(spark, tmp_path):
    path = f"file://{tmp_path}/shards"
    rows = [(i, "x" * i, s, k) for s, n in ((0, 3), (1, 5), (2, 1)) for k, i in enumerate(range(10 * s, 10 * s + n))]
    spark.createDataFrame(rows, "doc_id long, text string, shard int, slot long").write.partitionBy("shard").parquet(path)
    before = {f.name for f in (tmp_path / "shards" / "shard=0").iterdir()}
    resharding.reshard_files(resharding.stored(spark, path), path, 3)
    assert {f.name for f in (tmp_path / "shards" / "shard=0").iterdir()} == before
    got = resharding.stored(spark, path).collect()
    assert Counter(r.shard for r in got) == {0: 3, 1: 3, 2: 3} and sorted(r.doc_id for r in got) == sorted(r[0] for r in rows)


def test_op5_reads_its_rows_back_from_shard_files(spark, sf_dir, monkeypatch):
    at = []
    monkeypatch.setattr(queries, "shared_file", lambda *a: at.append(shared_file(*a)) or at[-1])
    got = queries.op5_sharding(spark, sf_dir)
    files = spark.read.parquet(at[0])
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    assert files.drop("shard", "slot").exceptAll(docs).count() == docs.exceptAll(files.drop("shard", "slot")).count() == 0
    assert files.select("doc_id", "shard", "slot").exceptAll(got.select("doc_id", "shard", "slot")).count() == 0
    empty = resharding.digests(docs.limit(0), shared_file(spark, "shards"))
    assert empty.count() == 0 and empty.columns == got.columns


def brute_turns(rows):
    by = defaultdict(list)
    for r in rows:
        by[r.conv_id].append(r)
    for k, v in by.items():
        v.sort(key=lambda r: (r.turn is not None, r.turn or 0, r.role or "", r.text or ""))
        said = "".join(f"{r.role or ''}\n{r.text or ''}\n" for r in v)
        loss = "".join(r.text or "" for r in v if r.role == "assistant")
        yield k, (len(v), hashlib.sha256(said.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())


def test_chat_windows_read_back(spark, sf_dir):
    hard = [(1, 0, "system", "be & kind <s>"), (1, 1, "us\ner>", None), (1, 2, "assistant", "&l <turn:n>x\n</turn>\n[INST]"), (None, 0, None, "t"), (1, 2, "assistant", "&a&l&b&n")]
    hard += [(2, i, ("user", "assistant")[i % 2], "long words " * (i * 17 % 90)) for i in range(120)] + [(3, None, "assistant", "z" * 9000), (3, None, "assistant", "z" * 9000)]
    turns = spark.createDataFrame(hard, "conv_id long, turn long, role string, text string").withColumn("pos", F.lit(1))
    turns = turns.select("conv_id", "turn", "role", "text").union(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    windows = chat_windows.format_windows(turns)
    got = {r.conv_id: tuple(r)[1:5] for r in chat_windows.conversation_digests(windows).collect()}
    assert got == dict(brute_turns(turns.collect()))
    sizes = [(r.text.count("<turn:"), r.n_new + r.n_context, r.n_context) for r in windows.collect()]
    assert all(a == b for a, b, _ in sizes) and max(c for *_, c in sizes) <= 3
    assert chat_windows.conversation_digests(chat_windows.format_windows(turns.limit(0))).count() == 0


@pytest.mark.parametrize("budget,history", [(512, 128), (96, 40), (20, 0)])
def test_windows_stay_within_the_budget(spark, sf_dir, budget, history):
    hard = [(2, i, ("user", "assistant")[i % 2], "long words " * (i * 17 % 40)) for i in range(90)] + [(3, 0, "system", "s" * 100), *((3, i, "user", "x" * (i % 50)) for i in range(1, 60)), (4, 0, "system", "s" * 4000), (4, 1, "user", "a"), (4, 2, "assistant", "b")]
    turns = spark.createDataFrame(hard, "conv_id long, turn long, role string, text string").union(spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text"))
    shared = 0
    for w in chat_windows.format_windows(turns, budget, history).collect():
        pieces = [x.split("\n", 1) for x in w.text.split("<turn:")[1:]]
        cost = [-(-(len(body) - len(chat_windows.CLOSE)) // 4) + 4 for _, body in pieces]
        assert sum(cost) == w.tokens
        system = cost[0] if pieces[0][0][2:] == "system" else 0
        new = [c for (head, _), c in zip(pieces, cost, strict=True) if head[0] == "n" and head[2:] != "system"]
        assert w.tokens <= budget or (len(new) <= 1 and system + sum(new) == w.tokens)
        shared += len(new) > 1
    assert shared or budget == 20


def test_op6_equals_its_sql(spark, sf_dir):
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW conversations AS SELECT * FROM '{sf_dir}/conversations.parquet'")
        got = db.execute(queries.oracle_sql()["op6_chat_windows"])
        names = [c[0] for c in got.description]
        want = sorted(got.fetchall())
    assert want and sorted(map(tuple, queries.op6_chat_windows(spark, sf_dir).select(*names).collect())) == want


def test_mixing_targets_and_takes(spark, sf_dir):
    rows = queries.op9_source_mixing(spark, sf_dir).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, queries.op9_source_mixing(spark, sf_dir).collect()))
    sizes, took, target, top = Counter(), Counter(), {}, Counter()
    for r in rows:
        sizes[r.source] += r["size"]
        took[r.source] += r.taken
        target[r.source] = r.target
        top[r.source] = max(top[r.source], r["size"])
        assert r.taken <= 2 * r["size"]
    names = sorted(sizes, key=lambda s: (s is None, s))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    want, budget, free = {}, 1.5 * sum(sizes.values()), set(names)
    while free:
        level = (budget - sum(want.values())) / sum(weight[s] for s in free)
        full = {s for s in free if level * weight[s] > 2 * sizes[s]}
        if not full:
            want |= {s: level * weight[s] for s in free}
            break
        want |= {s: 2.0 * sizes[s] for s in full}
        free -= full
    for s in names:
        assert target[s] == pytest.approx(want[s]) and abs(took[s] - target[s]) <= 2 * top[s]
    odd_rows = mixing.mix(odd(spark)).collect()
    assert len(odd_rows) == len(ROWS)
    n = sum(r.copies for r in odd_rows)
    assert mixing.mixed_documents(odd(spark)).count() == n and mixing.mixed_documents(odd(spark)).columns == odd(spark).columns
    assert mixing.mix(odd(spark).limit(0)).count() == 0
