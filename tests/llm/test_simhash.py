import random

import numpy as np
import xxhash

from farpoint.llm import simhash as S
from farpoint.llm.common import Staging
from farpoint.llm.components import connected_components


def brute_print(text):
    words = [w for w in (text or "").encode().lower().split()]
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(len(words) - 2, 1))] if words else []
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h)) if h else 0


def brute_components(ids, prints, limit=2):
    root = list(range(len(ids)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= limit:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    low = {}
    for i in range(len(ids)):
        r = find(i)
        low[r] = min(low.get(r, ids[i]), ids[i])
    return {ids[i]: low[find(i)] for i in range(len(ids))}


def test_documents_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = docs.select("doc_id", "text").collect()
    got = {r.doc_id: r for r in S.simhash_groups(spark, docs).collect()}
    prints = [brute_print(r.text) for r in rows]
    want = brute_components([r.doc_id for r in rows], prints)
    assert {k: r.component_id for k, r in got.items()} == want
    assert {k: r.fingerprint for k, r in got.items()} == {r.doc_id: f"{p:016x}" for r, p in zip(rows, prints, strict=True)}


def test_links_of_light_and_heavy_buckets(spark):
    rng = random.Random(5)
    prints = set()
    for _ in range(40):
        x = rng.getrandbits(64)
        for _ in range(12):
            prints.add(x)
            x ^= 1 << rng.randrange(64)
            if rng.random() < 0.5:
                x ^= 1 << rng.randrange(64)
    prints |= {0, (1 << 64) - 1, 1 << 63, (1 << 63) | 1}
    prints = sorted(prints)
    frame = spark.createDataFrame([(int(np.uint64(p).view(np.int64)),) for p in prints], "fp long")
    index = {int(np.uint64(p).view(np.int64)): i for i, p in enumerate(prints)}
    for heavy, limit in ((1024, 2), (1, 2), (20, 3), (1, 1)):
        want = brute_components(list(range(len(prints))), prints, limit)
        stage = Staging(spark, "test")
        roots = {index[r.node]: index[r.root] for r in connected_components(stage, S.near_links(stage, frame, heavy, limit)).collect()}
        groups = {}
        for i in range(len(prints)):
            groups.setdefault(roots.get(i, i), []).append(i)
        assert {i: min(g) for g in groups.values() for i in g} == want


def test_ring_levels_bound_a_bucket():
    for limit in (1, 2, 3, 5, 8, 15):
        levels = S.ring_levels(limit)
        assert levels[0][0] == 64 and all(a[0] - a[1] * a[2] == b[0] for a, b in zip(levels, levels[1:], strict=False))
        assert limit > 3 or levels[-1][0] - levels[-1][1] * levels[-1][2] <= S.FREE_BITS


def test_chain_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 90), (90, 95), (7, 7)], "a long, b long")
    got = {r.node: r.root for r in connected_components(Staging(spark, "test"), links).collect()}
    assert got == {i: 0 for i in range(61)} | {90: 90, 95: 90, 100: 90}


def test_edge_rows(spark):
    docs = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (2, "", "x"), (None, " \t", "x"), (5, "A b c", "x"), (6, "a B c", "x"), (7, "w " * 70_000, "x")], "doc_id long, text string, fp string")
    got = sorted(map(str, S.simhash_groups(spark, docs).collect()))
    assert len(got) == 7 and sum("component_id=1)" in x for x in got) == 4 and sum("component_id=5)" in x for x in got) == 2
    assert S.simhash_groups(spark, docs.limit(0)).count() == 0
