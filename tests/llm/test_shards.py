import hashlib

import numpy as np

from farpoint.llm import token_shards as T
from farpoint.llm.common import Staging


def test_feistel_is_a_permutation():
    for size in (1, 2, 3, 17, 1000, 4096, 4097):
        got = T.feistel(np.arange(size), size, 7)
        assert sorted(got.tolist()) == list(range(size))
    a, b = T.feistel(np.arange(1000), 1000, 7), T.feistel(np.arange(1000), 1000, 8)
    assert (a != b).mean() > 0.9 and abs(np.corrcoef(a, np.arange(1000))[0, 1]) < 0.15


def test_round_trip(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").where("doc_id < 60")
    extra = spark.createDataFrame([(None, None), (1000, ""), (1001, "x" * 30_000), (1001, "x" * 30_000)], "doc_id long, text string")
    docs = docs.unionByName(extra)
    stage, texts = Staging(spark, "test"), {}
    index = T.write_shards(spark, docs, stage, length=64, shard_sequences=100, rounds=3)
    rows = index.collect()
    back = {r.slot: np.frombuffer(bytes(r.tokens), "<u2") for r in T.read_shards(index, stage, 64, 100).collect()}
    assert sorted(back) == list(range(len(rows))) == sorted(r.slot for r in rows)
    for r in sorted(rows, key=lambda r: r.chunk):
        ids = back[r.slot]
        assert len(ids) == r.n_tokens and r.shard == r.slot // 100
        if r.doc_id != 1001:
            texts.setdefault(r.doc_id, []).extend(ids.tolist())
    decode = T.encoding(T.TOKENIZER).decode
    assert all(ids[-1] == T.END_OF_TEXT for ids in texts.values())
    assert {d: decode(ids[:-1]) for d, ids in texts.items()} == {r.doc_id: r.text or "" for r in docs.collect() if r.doc_id != 1001}
    later = T.read_shards(index, stage, 64, 100, resume_at=137)
    assert sorted(r.slot for r in later.collect()) == list(range(137, len(rows)))


def test_query_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = T.shard_round_trip(spark, docs).collect()
    want = set()
    for d in docs.collect():
        ids = np.array([*T.encoding(T.TOKENIZER).encode_ordinary(d.text), T.END_OF_TEXT], "<u2")
        want |= {(d.doc_id, c, hashlib.sha256(ids[c * T.LENGTH : (c + 1) * T.LENGTH].tobytes()).hexdigest()) for c in range(-(-len(ids) // T.LENGTH))}
    assert {(r.doc_id, r.chunk, r.tokens_sha256) for r in rows} == want and len(rows) == len(want)
    assert T.shard_round_trip(spark, docs.limit(0)).count() == 0


def test_columns_of_other_meaning(spark):
    docs = spark.createDataFrame([(1, "a b c", 9, 9, "x"), (1, "a b c", 9, 9, "x"), (None, None, 9, 9, "x"), (2, "long " * 60_000, 9, 9, "x")], "doc_id long, text string, slot int, shard int, part string")
    rows = T.shard_round_trip(spark, docs).collect()
    assert sorted(r.slot for r in rows) == list(range(len(rows))) and sum(r.doc_id == 1 for r in rows) == 2 and sum(r.doc_id is None for r in rows) == 1
    ids = np.array([*T.encoding(T.TOKENIZER).encode_ordinary("long " * 60_000), T.END_OF_TEXT], "<u2")
    assert sum(r.n_tokens for r in rows if r.doc_id == 2) == len(ids)
