import random

import numpy as np

from farpoint.llm import similar
from farpoint.llm import simhash as S


def shingles(text):
    words = (text or "").lower().split()
    return {" ".join(words[i : i + 5]) for i in range(max(len(words) - 4, 1))} if words else set()


def brute_left(docs):
    """(id, text) of one row of each group over two bits or a 5-word Jaccard of 0.8."""
    prints, sets = [S.fingerprint(t, similar.SHINGLE) for _, t in docs], [shingles(t) for _, t in docs]
    root = list(range(len(docs)))
    for i in range(len(docs)):
        for j in range(i):
            near = sets[i] and sets[j] and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])
            if near or (prints[i] ^ prints[j]).bit_count() <= 2:
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    best = {}
    for i, (doc, text) in enumerate(docs):
        key = (doc is None, doc or 0)
        if root[i] not in best or key < best[root[i]][0]:
            best[root[i]] = (key, (doc, text))
    return sorted(str(x) for _, x in best.values())


def edited():
    rng, docs = random.Random(8), []
    vocab = [f"w{i}" for i in range(300)]
    shared = [rng.choice(vocab) for _ in range(60)]
    for n in (4, 5, 8, 9, 30, 100, 100, 300):
        base = [rng.choice(vocab) for _ in range(n)] + (shared if n == 30 else [])
        for edits in (0, 0, 1, 2, 3, 5, 8):
            words = list(base)
            for _ in range(edits):
                words[rng.randrange(len(words))] = rng.choice(vocab)
            docs.append((len(docs), " ".join(words) + " " * edits))
    return [*docs, *((len(docs) + i, " ".join([*(rng.choice(vocab) for _ in range(20)), *shared])) for i in range(12))]


def test_similar_texts_go_whatever_their_bits(spark, monkeypatch):
    docs = edited()
    frame = spark.createDataFrame([(d, t, "s") for d, t in docs], "doc_id long, text string, source string")
    want = brute_left(docs)
    for crowd in (similar.CROWD, 2):  # 2: keys of two and three shingles
        monkeypatch.setattr(similar, "CROWD", crowd)
        assert sorted(str((r.doc_id, r.text)) for r in S.drop_near_duplicates(spark, frame).collect()) == want
    groups = S.simhash_groups(spark, frame, shingle=similar.SHINGLE).collect()
    assert len(want) < len({r.component_id for r in groups})  # two bits alone leave more
    assert S.drop_near_duplicates(spark, frame.limit(0)).count() == 0


def test_prefixes_of_similar_sets_meet():
    assert [similar.prefix_size(n) for n in (0, 1, 4, 5, 10)] == [0, 1, 1, 2, 3]


def test_pairs_inside_keys():
    rng = np.random.default_rng(3)
    key, n = np.sort(rng.integers(0, 6, 120)), rng.integers(1, 40, 120)
    order = np.lexsort([n, key])
    key, n = key[order], n[order]
    root = rng.integers(0, 3, 120)
    root[key == 2] = 1
    a, b = similar.cross_pairs(key, n, root)
    want = {(i, j) for i in range(120) for j in range(i + 1, 120) if key[i] == key[j] and root[i] != root[j] and 5 * n[i] >= 4 * n[j]}
    assert set(zip(a.tolist(), b.tolist(), strict=True)) == want
    a, b = similar.hub_pairs(key, n)
    hubs, want = {}, set()
    for i in range(120):
        if key[i] not in hubs or 4 * n[i] > 5 * n[hubs[key[i]]]:
            hubs[key[i]] = i
        else:
            want.add((i, hubs[key[i]]))
    assert set(zip(a.tolist(), b.tolist(), strict=True)) == want
    assert [len(x) for x in similar.cross_pairs(key[:0], n[:0], root[:0])] == [0, 0] == [len(x) for x in similar.hub_pairs(key[:0], n[:0])]
