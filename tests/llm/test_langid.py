import zlib

import numpy as np
from pyspark.sql import functions as F

from farpoint.llm import langid as L


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = L.identify(docs, L.train(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert len(got) > 150 and np.mean([r.lang_pred == r.lang for r in got]) > 0.97
    assert all(0 <= r.score <= 1 for r in got)


def test_split_and_what_a_prediction_may_see(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    net = L.train(docs)
    rows = L.identify(docs, net).collect()
    assert {r.doc_id: r.held_out for r in rows} == {r.doc_id: zlib.crc32(str(r.doc_id).encode()) % 4 == 2 for r in rows}
    told = {r.doc_id: (r.lang_pred, r.score) for r in rows}
    other = docs.withColumns({"lang": F.lit("xx"), "source": F.lit("s"), "n_chars": F.lit(0), "doc_id": F.col("doc_id") + 7_000})
    assert {r.doc_id - 7_000: (r.lang_pred, r.score) for r in L.identify(other, net).collect()} == told
    hidden = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2
    wrong = docs.withColumn("lang", F.when(hidden, F.lit("xx")).otherwise(F.col("lang"))).withColumn("text", F.when(hidden, F.lit("qq")).otherwise(F.col("text")))
    again = L.train(wrong)  # what is held out teaches nothing
    assert again.classes == net.classes and all(np.array_equal(again.p[k], net.p[k]) for k in net.p)


def test_gradient():
    rng = np.random.default_rng(0)
    net = L.ByteNet(["a", "b", "c"])
    x, y = rng.integers(0, 256, (5, L.LENGTH)), np.array([0, 1, 2, 1, 0])
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    _, grad = net.step(x, y)
    for name in net.p:
        flat = net.p[name].reshape(-1)
        for i in rng.integers(0, flat.size, 4):
            keep, eps = flat[i], 1e-5
            flat[i] = keep + eps
            up = net.step(x, y)[0]
            flat[i] = keep - eps
            down = net.step(x, y)[0]
            flat[i] = keep
            assert abs((up - down) / (2 * eps) - grad[name].reshape(-1)[i]) < 1e-4


def test_predictor_is_the_network():
    rng = np.random.default_rng(1)
    net = L.ByteNet(["a", "b"])
    x = rng.integers(0, 256, (7, L.LENGTH)).astype(np.uint8)
    t = net._tables()
    h = np.concatenate([np.maximum(sum(t[w][j][x[:, j : L.LENGTH - w + 1 + j]] for j in range(w)).max(1), 0) for w in L.WIDTHS], 1)
    assert np.allclose(net.predictor()(x), L.softmax(h @ net.p["out"] + net.p["bias"]), atol=1e-5)


def test_edge_rows(spark):
    rows = [(1, None, "en", 0), (2, "12 !", None, 0), (3, "", "fr", 0), (None, "the and", "en", 0), (5, "le la " * 9000, "fr", 0), (5, "le la " * 9000, "fr", 0), (7, "the of and", "en", 0)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, score int")
    got = L.identify(frame, L.train(frame)).collect()
    assert len(got) == 7 and sorted(r.doc_id or 0 for r in got if r.lang_pred == "und" and r.score == 0) == [1, 2, 3]
    assert L.train(frame.limit(0)) is None and L.identify(frame.limit(0), None).count() == 0
    assert {r.lang_pred for r in L.identify(frame, None).collect()} == {"und"}
