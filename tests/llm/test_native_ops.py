import hashlib
import re

from pyspark.sql import functions as F

from farpoint.llm.decontam import contamination, drop_contaminated
from farpoint.llm.exact_dedup import drop_exact_duplicates, exact_dedup

DOCS = [
    (1, None, "a"), (2, "", "b"), (3, "x  y\t\nz", "c"), (4, "x y z", "d"), (4, "x y z", "e"), (None, "x y z", "f"), (7, "q", "g"), (8, "w" * 50_000, "h"),
]


def test_exact_dedup_rows(spark):
    docs = spark.createDataFrame(DOCS, "doc_id long, text string, keep_id string")
    for digest in (F.md5, lambda c: F.substring(F.md5(c), 1, 2).substr(1, 2), lambda c: F.lit("00")):
        got = exact_dedup(docs, digest=digest).collect()
        assert len(got) == len(DOCS)
        seen = {(r.doc_id, r.keep_id, r.group_size) for r in got}
        assert seen == {(1, 1, 2), (2, 1, 2), (3, 3, 4), (4, 3, 4), (None, 3, 4), (7, 7, 1), (8, 8, 1)}
        assert sum(r.kept for r in got) == 4
        assert {r.text_sha256 for r in got if r.doc_id == 3} == {hashlib.sha256(b"x y z").hexdigest()}
    assert exact_dedup(docs.limit(0)).count() == 0
    again = spark.createDataFrame([(5, "a"), (5, "a")], "doc_id long, text string")
    assert sorted(r.kept for r in exact_dedup(again).collect()) == [False, True]
    assert drop_exact_duplicates(docs).where("doc_id in (3,7)").count() == 2
    shared = [(1, "a"), (1, "b"), (1, "a"), (None, "c"), (None, "d"), (None, "a"), (2, "c")]
    left = drop_exact_duplicates(spark.createDataFrame(shared, "doc_id long, text string")).collect()
    assert sorted(map(str, map(tuple, left))) == sorted(map(str, [(1, "a"), (1, "b"), (None, "d"), (2, "c")]))


def brute(docs, items, size=13):
    def words(t):
        return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))

    out = []
    wins = {}
    for item, text in items:
        w = words(text)
        for s in range(max(len(w) - size + 1, 1) if w else 0):
            wins.setdefault(tuple(w[s : s + size]), set()).update([] if item is None else [str(item)])
    for doc, text in docs:
        w, hit, found = words(text), set(), set()
        for n in {len(x) for x in wins}:
            for s in range(len(w) - n + 1):
                if (x := wins.get(tuple(w[s : s + n]))) is not None:
                    hit |= set(range(s, s + n))
                    found |= x
        out.append((doc, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return out


def test_contamination_against_brute_force(spark, sf):
    long = " ".join(f"w{i}" for i in range(40))
    items = [(1, long), (10, "Alpha BETA"), (2, "beta"), (3, None), (4, "..."), (5, " ".join(f"w{i}" for i in range(5, 18))), (5, "Alpha BETA"), (6, "the the the"), (None, "nobody owns this passage")]
    docs = [
        (1, None), (2, ""), (3, "!!"), (4, f"x {long} y"), (5, "alpha-beta gamma " * 30), (6, "é Alpha É beta" + " z" * 100), (7, "w5 " + long[3:]),
        (8, "the " * 300), (9, "beta"), (9, "beta"), (None, "beta"), (11, "w0 w1 w2 w3 w4"),
        (12, "nobody owns this passage"), (13, "long " * 150_000 + long),
    ]
    frame = spark.createDataFrame(docs, "doc_id long, text string").withColumn("token", F.lit("t")).withColumn("n_words", F.lit(1))
    bench = spark.createDataFrame(items, "item_id long, text string").withColumn("win", F.lit(0))
    want = sorted(map(str, brute(docs, items)))
    for block in (100_000, 3):
        got = sorted(str(tuple(r)) for r in contamination(spark, frame, bench, block_windows=block).collect())
        assert got == want
    assert [r.n_hit for r in contamination(spark, frame, bench.limit(0)).collect()] == [0] * len(docs)
    assert contamination(spark, frame.limit(0), bench).count() == 0
    left = {r.doc_id for r in drop_contaminated(spark, frame, bench).collect()}
    assert left == {d for d, *_, bad in brute(docs, items) if not bad}
