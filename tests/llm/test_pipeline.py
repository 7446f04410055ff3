import ast
import hashlib

import pyarrow as pa

import corpus_pipeline as P
from farpoint.llm import langid, sp_sample
from tests.llm.test_lines import brute as brute_lines
from tests.llm.test_native_ops import brute as brute_contamination
from tests.llm.test_similar import brute_left


def test_pipeline_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    bench = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    texts = {r.doc_id: r.text for r in docs.collect()}
    net = langid.train(docs)
    names, score = langid.Predictor(net)(pa.array(list(texts.values())))
    left = [(d, t) for (d, t), n, s in zip(texts.items(), names, score, strict=True) if n != "und" and s >= 0.35]
    left = [(r[0], r[1]) for r in map(ast.literal_eval, brute_lines(left, 50))]
    left = [(r[0], r[1]) for r in map(ast.literal_eval, brute_left(left))]
    bad = {r[0] for r in brute_contamination(left, bench) if r[5]}
    left = dict((d, t) for d, t in left if d not in bad)
    rows = P.run(spark, sf).collect()
    assert {r.doc_id for r in rows} == set(left) and 50 < len(left) < len(texts)
    assert {(r.doc_id, r.decoded_sha256) for r in rows} == {(d, hashlib.sha256(t.encode()).hexdigest()) for d, t in left.items()}
    assert sum(r.sample_no == 1 for r in rows) == len(left) and max(r.sample_no for r in rows) == sp_sample.SAMPLES


def test_stages_keep_columns_and_clean_documents(spark, sf):
    docs = spark.createDataFrame(
        [(1, "the and of that " * 20 + "unlike", "en", "s", 1), (2, None, "en", "s", 0), (3, "...", "en", "s", 3), (5, "le la des un " * 9, "fr", "s", 1), (5, "le la des un " * 9, "fr", "s", 1)],
        "doc_id long, text string, lang string, source string, n_chars long",
    )
    for _, step in P.STAGES[:-1]:
        docs = step(spark, docs, sf)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert sorted(r.doc_id for r in docs.collect()) == [1, 5]
    empty = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, step in P.STAGES:
        empty_out = step(spark, empty, sf)
        assert empty_out.count() == 0
