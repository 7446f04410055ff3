import random

import numpy as np
import pyarrow as pa
import pytest

from farpoint.llm import substring_dedup as S


def brute(docs, window=S.WINDOW):
    split = [(d, (t or "").encode().split()) for d, t in docs]
    seen = {}
    for _, w in split:
        for s in range(len(w) - window + 1):
            seen[tuple(w[s : s + window])] = seen.get(tuple(w[s : s + window]), 0) + 1
    out = []
    for d, w in split:
        gone = set()
        for s in range(len(w) - window + 1):
            if seen[tuple(w[s : s + window])] > 1:
                gone |= set(range(s, s + window))
        out.append((d, len(w), len(gone), b" ".join(x for i, x in enumerate(w) if i not in gone).decode()))
    return sorted(map(str, out))


def texts():
    rng = random.Random(3)
    vocab = [f"w{i}" for i in range(400)] + ["é", "ß"]
    passages = [[rng.choice(vocab) for _ in range(n)] for n in (34, 35, 36, 60, 200)]
    docs = [(1, None), (2, ""), (3, "a b"), (4, "same " * 90), (5, "x\x0by " * 30), (None, "z " + " ".join(passages[3]))]
    for i in range(80):
        words = [rng.choice(vocab) for _ in range(rng.randrange(5, 120))]
        for _ in range(rng.randrange(3)):
            at = rng.randrange(len(words))
            p = rng.choice(passages)
            words[at:at] = p[: rng.randrange(20, len(p) + 1)]
        docs.append((10 + i, rng.choice([" ", "\n", "  "]).join(words)))
    hot = " ".join(rng.choice(vocab) for _ in range(80))
    docs += [(150 + i, f"a{i} {hot} " + " ".join(rng.choice(vocab) for _ in range(rng.randrange(40)))) for i in range(12)]
    docs += [(170 + i, hot) for i in range(5)] + [(180, "short copy"), (181, "short copy")] + [(190, hot + " z")] * 9
    return docs + [(20, docs[16][1]), (20, docs[16][1]), (99, docs[30][1]), (99, "the  " * 34 + docs[31][1])]


def test_against_brute_force(spark):
    docs = texts()
    frame = spark.createDataFrame([(*d, "x") for d in docs], "doc_id long, text string, spans string")
    want = brute(docs)
    for group_rows in (S.GROUP_ROWS, 2):
        assert sorted(str(tuple(r)) for r in S.substring_dedup(spark, frame, group_rows).collect()) == want
    assert S.substring_dedup(spark, frame.limit(0)).count() == 0


def test_one_key_too_large_for_a_group(monkeypatch):
    """Rows of one key that no deal takes apart come in several orders, which tell their windows."""
    rng = random.Random(9)
    words = [f"w{i}" for i in range(60)]
    rows = [(7, 0, 1, i, 1, 0, " ".join([rng.choice(words) for _ in range(3)] + words[:40]).encode()) for i in range(50)] + [(8, 0, 1, 90, 1, 0, " ".join(words[5:45]).encode())]
    names = ["part", "deal", "deals", "doc_id", "body_hash", "first", "body"]
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=names)
    monkeypatch.setattr(S, "GROUP_WORDS", 500)
    out = pa.Table.from_batches(list(S._trees(iter([batch])))).to_pylist()
    told = [r for r in out if r["node"] is not None]
    assert {r["doc_id"] for r in out if r["node"] is None} == set(range(50)) and 90 not in {r["doc_id"] for r in told}
    assert len({r["node"] for r in told}) < len(told)
    with pytest.raises(ValueError):
        S.node_of(np.zeros((1 << S.RANK_BITS) + 1, np.int64))


def test_long_text(spark):
    rng = random.Random(11)
    words = [str(rng.randrange(5000)) for _ in range(400_000)]
    docs = [(1, " ".join(words)), (2, " ".join(words[1000:1050]) + " end"), (3, "same " * 200_000)]
    got = {r.doc_id: (r.n_words, r.n_removed) for r in S.substring_dedup(spark, spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == {1: (400_000, 50), 2: (51, 50), 3: (200_000, 200_000)}


def test_long_text_in_pieces(monkeypatch):
    monkeypatch.setattr(S, "SCAN_WORDS", 50)
    rng = np.random.default_rng(1)
    h = rng.integers(0, 2**63, 500).astype(np.uint64)
    windows = set()
    for lo in range(0, len(h) - S.WINDOW + 1, 50):
        piece = h[lo : lo + 50 + S.WINDOW - 1]
        _, _, a, b = S.stretches(piece, np.array([len(piece)]))
        for x, y in zip(a + lo, b + lo, strict=True):
            windows |= set(range(x, y + 1))
    assert windows == set(range(len(h) - S.WINDOW + 1))


def test_nodes_are_equal_windows():
    rng = np.random.default_rng(2)
    ids = rng.integers(0, 2, 3000)
    for window in (3, 5, 9, 20, 35):
        node, leaves = S.node_of(ids, window)
        seen = {}
        for i in range(len(ids) - window + 1):
            seen.setdefault(ids[i : i + window].tobytes(), []).append(i)
        for group in seen.values():
            assert len(set(node[group])) == 1 and leaves[node[group[0]]] == len(group)
