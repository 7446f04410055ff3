import hashlib
import math

import numpy as np
import pytest
import sentencepiece

from farpoint.llm import sp_sample as S


@pytest.fixture(scope="module")
def toy():
    special = ["<unk>", "<s>", "</s>"] + [f"<0x{i:02X}>" for i in range(256)]
    return S.Vocabulary([*special, "▁", "a", "b", "c", "ab", "▁a", "bc", "abc", "▁ab", "▁▁"])


def brute(vocab, text):
    """All segmentations with their normalised log-probabilities."""
    s = (" " + text).replace(S.SPACE, "\x00")
    by = {p.replace(S.SPACE, " "): i for i, p in enumerate(vocab.pieces) if i >= 259}

    def paths(at):
        if at == len(s):
            return [((), 0.0)]
        out = []
        c = s[at].replace("\x00", S.SPACE)
        if s[at] not in by:
            b = c.encode()
            out += [((*(3 + x for x in b), *ids), w + len(b) * vocab.byte_weight) for ids, w in paths(at + 1)]
        for piece, i in by.items():
            if s.startswith(piece, at):
                out += [((i, *ids), w + vocab.weight[i]) for ids, w in paths(at + len(piece))]
        return out

    found = dict(paths(0))
    total = np.logaddexp.reduce(list(found.values()))
    return {k: v - total for k, v in found.items()}


TEXTS = ["abc", "a", "ab  abc b", " ab", "b ", "   ", "aé▁b", "abcabc\nab abc", "zz"]


def test_all_segmentations_and_their_probabilities(toy):
    for near in (1, 2, 12):
        got = S.sample(toy, TEXTS, list(range(len(TEXTS))), 3000, near)
        for text, rows in zip(TEXTS, got, strict=True):
            want = brute(toy, text)
            assert {tuple(ids) for ids, *_ in rows} == set(want) and len(rows) == len(want)
            for ids, lp, value, score in rows:
                assert abs(lp - want[tuple(ids)]) < 1e-9 and score == 1.0
                assert S.decode(toy, ids).decode() == text
            values = [r[2] for r in rows]
            assert values == sorted(values, reverse=True)


def test_distribution_without_replacement(toy):
    text, n, k = "abcab abc", 6000, 3
    want = brute(toy, text)
    for near in (2, 12):
        rows = S.sample(toy, [text] * n, [S.mix_one(i) for i in range(n)], k, near)
        first, second, weight = {}, {}, {}
        for r in rows:
            ids = [tuple(x[0]) for x in r]
            assert len(set(ids)) == k
            first[ids[0]] = first.get(ids[0], 0) + 1 / n
            second[ids[1]] = second.get(ids[1], 0) + 1 / n
            for x in r:
                weight[tuple(x[0])] = weight.get(tuple(x[0]), 0) + math.exp(x[1]) / x[3] / n
        p = {i: math.exp(lp) for i, lp in want.items()}
        for i in want:
            assert abs(first.get(i, 0) - p[i]) < 5 * math.sqrt(p[i] / n) + 0.001
            q = sum(p[j] * p[i] / (1 - p[j]) for j in want if j != i)
            assert abs(second.get(i, 0) - q) < 5 * math.sqrt(q / n) + 0.001
        assert abs(sum(weight.values()) - 1) < 0.05  # the inclusion scores weigh without bias


def test_documents_round_trip(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = S.sampled_encodings(docs, 3, with_ids=True).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    model = sentencepiece.SentencePieceProcessor(model_file=S.MODEL)
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, {})[r.sample_no] = r
        assert model.decode(r.ids) == texts[r.doc_id]
        assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()
        assert r.log_prob <= 0 and 0 <= r.inclusion <= 1
    assert set(by) == set(texts) and all(len({r.ids_sha256 for r in v.values()}) == 3 for v in by.values())
    again = {(r.doc_id, r.sample_no): r.ids_sha256 for r in S.sampled_encodings(docs.repartition(7), 3).collect()}
    assert again == {(r.doc_id, r.sample_no): r.ids_sha256 for r in rows}


def test_edge_rows(spark):
    odd = "x" * 3000 + " ▁ \U0001f600퟿  "
    rows = [(1, None, 1), (2, "", 1), (None, "a b", 1), (4, odd, 1), (5, "\n\n  ", 1), (5, "\n\n  ", 1)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, seed int")
    got = S.sampled_encodings(frame).collect()
    assert sorted(r.doc_id or 0 for r in got) == [0, 0, 1, 2, 4, 4, 5, 5, 5, 5]
    assert {r.decoded_sha256 for r in got if r.doc_id == 4} == {hashlib.sha256(odd.encode()).hexdigest()}
    assert S.sampled_encodings(frame.limit(0)).count() == 0


def test_samples_do_not_depend_on_the_batch(toy):
    texts = ["abcab abc " * 40, "ab", "bc " * 200]
    alone = [S.sample(toy, [t], [i], 2)[0] for i, t in enumerate(texts)]
    for again, want in zip(S.sample(toy, texts, [0, 1, 2], 2), alone, strict=True):
        assert [(ids.tolist(), lp, value, score) for ids, lp, value, score in again] == [(ids.tolist(), lp, value, score) for ids, lp, value, score in want]


def test_very_long_text(spark):
    text = "many words of one text " * 20_000
    rows = S.sampled_encodings(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()
    assert len(rows) == S.SAMPLES and {r.decoded_sha256 for r in rows} == {hashlib.sha256(text.encode()).hexdigest()}
