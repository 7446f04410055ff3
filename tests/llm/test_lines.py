import random

from farpoint.llm import intervals as I
from farpoint.llm import line_dedup as L


def brute(docs, least):
    """Every run of ``least`` characters or more that an earlier place holds goes."""
    seen, out = set(), []
    for doc, text in sorted(docs, key=lambda d: (d[0] is not None, d[0] or 0)):
        lines, gone = [] if text is None else text.split("\n"), set()
        for s in range(len(lines)):
            for e in range(s + 1, len(lines) + 1):
                if sum(map(len, lines[s:e])) >= least:
                    key = tuple(lines[s:e])
                    if key in seen:
                        gone |= set(range(s, e))
                    seen.add(key)
        out.append((doc, None if text is None else "\n".join(x for i, x in enumerate(lines) if i not in gone), len(lines), len(gone)))
    return sorted(map(str, out))


def test_against_brute_force(spark):
    rng = random.Random(4)
    vocab = ["", "a", "bb", "c" * 9, "d" * 25, "é" * 12, "e" * 60, "f" * 30]
    docs = [(None, "\n".join("xyz" for _ in range(40))), (1, None), (2, ""), (3, "\n" * 70 + "e" * 60), (4, "t" * 70 + "\nend"), (5, "t" * 70 + "\nend"), (6, "A" * 60 + "\nshort tail"), (7, "\n".join(["four times 12"] * 4))]
    docs += [(8, "A" * 60 + "\nshort tail"), (9, "\n".join(["four times 12"] * 4))]
    for i in range(60):
        docs.append((10 + i, "\n".join(rng.choice(vocab) + rng.choice(["", "", str(rng.randrange(30))]) for _ in range(rng.randrange(1, 40)))))
    docs += [(200, docs[20][1]), (200, docs[20][1]), (201, docs[30][1] + "\nnew")]
    frame = spark.createDataFrame([(t, d, 5) for d, t in docs], "text string, doc_id long, n_lines int")
    for least in (50, 8):
        got = L.line_dedup(spark, frame, least).select("doc_id", "text", "n_lines", "n_removed").collect()
        assert sorted(str(tuple(r)) for r in got) == brute(docs, least)
    assert L.line_dedup(spark, frame.limit(0)).count() == 0


def test_runs_of_many_lengths_and_ranges(spark, monkeypatch):
    """Small ranges, so that classes and intervals reach over borders."""
    rng = random.Random(7)
    base = [rng.choice("abc") for _ in range(150)]
    docs = [(i, "\n".join(base[a : a + n] + [rng.choice(["x", "y", f"u{i}"])] + base[b : b + m])) for i, (a, n, b, m) in enumerate((rng.randrange(100), rng.randrange(1, 50), rng.randrange(100), rng.randrange(20)) for _ in range(50))]
    docs += [(100, "\n".join("ab" * 40)), (101, "\n".join("ab" * 30))]
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    for key, value in {"spark.sql.shuffle.partitions": "20", "spark.sql.adaptive.coalescePartitions.enabled": "false"}.items():
        before = spark.conf.get(key)
        spark.conf.set(key, value)
        try:
            for least in (3, 12):
                got = L.line_dedup(spark, frame, least).select("doc_id", "text", "n_lines", "n_removed").collect()
                assert sorted(str(tuple(r)) for r in got) == brute(docs, least)
        finally:
            spark.conf.set(key, before)


def test_scan_in_ranges_is_that_of_all():
    rng = random.Random(5)
    for _ in range(300):
        n = rng.randrange(1, 40)
        places = [(1, x, 0, 0) for x in rng.sample(range(100), n)]
        common = [0, *(rng.choice([0, 1, 2, 3, 5, 5]) for _ in range(n - 1))]
        want = []
        for i in range(n):
            best = 0
            for j in range(n):
                if places[j] < places[i]:
                    best = max(best, min(common[min(i, j) + 1 : max(i, j) + 1]))
            want.append(best)
        cuts = sorted(rng.sample(range(1, n), min(n - 1, rng.randrange(4))))
        parts = [range(a, b) for a, b in zip([0, *cuts], [*cuts, n], strict=True)]
        scans, rows = [], []
        for part in parts:
            one, out = I.Scan(), []
            for i in part:
                out += one.add(i, places[i], common[i], 1)
            rows.append(out + one.end())
            scans.append(one)
        left, right, lefts, rights = [], [], [], []
        for one in scans:
            lefts.append(left)
            left = I.cut_down(left, one.through, one.closing)
        for one in reversed(scans):
            rights.append(right)
            right = I.cut_down(right, one.through, one.opening)
        got = {}
        for part, low, high in zip(rows, lefts, reversed(rights), strict=True):
            for rank, place, copied, before, behind in part:
                got[rank] = max(copied, min(before, I.earlier_place(low, place)), min(behind, I.earlier_place(high, place)))
        assert [got[i] for i in range(n)] == want


def test_very_long_texts(spark):
    many = "\n".join(f"line {i} of a very long text" for i in range(60_000))
    docs = [(1, many), (2, "new\n" + many), (3, "x" * 2_000_000), (4, "x" * 2_000_000 + "\nend"), (5, "\n" * 50_000)]
    got = {r.doc_id: (r.n_lines, r.n_removed, r.text) for r in L.line_dedup(spark, spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got[1][:2] == (60_000, 0) and got[2] == (60_001, 60_000, "new") and got[3][:2] == (1, 0)
    assert got[4] == (2, 1, "end") and got[5][:2] == (50_001, 0)


def test_window_lines():
    assert L.window_lines([10, 40, 0, 5], 50) == [2, 0, 0, 0]
    assert L.window_lines([0, 0, 50, 1], 50) == [3, 2, 1, 0]
    assert L.window_lines([], 50) == []
