import hashlib
import random

from farpoint.llm import chat, warc
from farpoint.llm.common import Staging


def test_escape_round_trip():
    rng = random.Random(1)
    for _ in range(3000):
        text = "".join(rng.choice("<\\|>a\n") for _ in range(rng.randrange(12)))
        assert chat.unescape(chat.escape(text)) == text and "<|" not in chat.escape(text)
        role = text + "r"
        assert chat.unescape_role(chat.escape_role(role)) == role and "\n" not in chat.escape_role(role)


def test_spans_and_rewriting_template():
    turns = [("system", ""), ("user", "<|im_end|>"), ("assistant", "|a<"), ("assistant", ""), ("user", "b"), ("assistant", "ab")]
    appends, [(text, spans)] = chat.locate(chat.marked_template, turns)
    assert appends and chat.parse_marked(text) == turns
    assert [chat.unescape(text[s[3] : s[4]]) for s in spans] == [t for _, t in turns]
    assert "".join(text[s[1] : s[2]] for s in spans) == text

    def forgets(turns):
        return "".join(f"[{r}:{t if i == len(turns) - 1 else '...'}]" for i, (r, t) in enumerate(turns))

    appends, examples = chat.locate(forgets, [("user", "hello"), ("assistant", "one"), ("user", "again"), ("assistant", "two")])
    assert not appends and [x[s[0][3] : s[0][4]] for x, s in examples] == ["one", "two"]


def test_long_conversations_are_linear_and_checked():
    rng = random.Random(2)
    turns = [(rng.choice(["user", "assistant"]), rng.choice(["<|", "a", "", "long " * 9])) for _ in range(150)]
    for template in (chat.marked_template, lambda t: "<s>" + chat.marked_template(t)):
        got = chat.locate(template, turns, context=4)
        assert got == chat.locate(template, turns, context=1000) and got[0]
        assert got[1][0][0] == template(turns)

    def forgets_far(turns):
        return chat.marked_template(turns[-40:])

    assert chat.locate(forgets_far, turns, context=4) == chat.locate(forgets_far, turns, context=1000)
    assert not chat.locate(forgets_far, turns, context=4)[0]

    def hides_system(turns):
        return chat.marked_template([t for t in turns if t[0] != "system"] if turns and turns[-1][0] == "tool" else turns)

    asked = [("system", "s"), *((("user", "q") if i % 2 else ("assistant", "a")) for i in range(59))]
    asked[37] = ("tool", "t")
    appends, examples = chat.locate(hides_system, asked)
    assert not appends and [x for x, _ in examples] == [hides_system(asked[: i + 1]) for i, (r, _) in enumerate(asked) if r == "assistant"]
    assert all(x[s[0][3] : s[0][4]] == "a" for x, s in examples)
    a, b = "x" * 1000 + "ab", "x" * 1000 + "ba"
    assert chat.common(a, b) == 1000 and chat.common(a, a[:5]) == 5 and chat.common("", a) == 0 and chat.common("q", a) == 0


def test_chat_edge_rows(spark):
    rows = [(1, 2, "assistant", None, 9), (1, 1, None, "q", 9), (None, 1, "assistant", "x<|y", 9), (2, 1, "assistant", "a", 9), (2, 1, "assistant", "a", 9), (3, 0, "user\nassistant", "t" * 100_000, 9)]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, turns int")
    got = {r.conv_id: r for r in chat.chat_digests(spark, frame).collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert set(got) == {1, None, 2, 3}
    assert (got[1].n_turns, got[1].turns_sha256, got[1].loss_chars) == (2, sha("\nq\nassistant\n\n"), 0)
    assert (got[None].loss_chars, got[None].loss_sha256) == (4, sha("x<|y"))
    assert got[2].loss_sha256 == sha("aa") and got[3].turns_sha256 == sha("user\nassistant\n" + "t" * 100_000 + "\n")
    assert chat.chat_digests(spark, frame.limit(0)).count() == 0


def test_conversations_in_parts(spark):
    rng = random.Random(3)
    rows = [(c, t, rng.choice(["user", "assistant"]), rng.choice(["<|", "a", None, "x y"])) for c in (1, 2, 3, None) for t in range(rng.choice([3, 90]))]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    whole = sorted(map(str, chat.chat_digests(spark, frame).collect()))
    assert sorted(map(str, chat.chat_digests(spark, frame, part_turns=7).collect())) == whole
    for context in (1, None):
        parts = chat.format_chats(frame, part_turns=7, context=context).where("conv_id = 1").orderBy("part").collect()
        one = chat.format_chats(frame, context=context).where("conv_id = 1").collect()
        assert len(one) == 1 and one[0].append_only and "".join(p.formatted for p in parts) == one[0].formatted
        assert len(parts) == 1 or parts[1].append_only is (context and True)


def test_warc_boundaries(spark):
    inner = warc.record_bytes(77, "http://fake/", b"fake payload", None, False, "1970-01-01T00:00:00Z").decode()
    big = "p" * 1500
    rows = [(1, "http://a/é x", inner * 3, 0), (2, None, None, 0), (3, "u\nWARC-Type: x", "WARC/1.1\r\n" * 50, 0), (None, "n", "<p>é", 0), (9, "z", inner * 90, 0)]
    rows += [(i, "c", big, 0) for i in (10, 11, 12, 12)] + [(20, "s", "short", 0), (21, "s", "short", 0), (22, "d", "d" * 20_000, 0), (None, "c", big, 0)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string, refers_to int")
    want = []
    for page, _, html, _ in rows:
        data = (html or "").encode()
        again = html == big and page != 12
        want.append((page, len(data), hashlib.sha1(data).hexdigest(), "revisit" if again else "response", 12 if again else None))
    assert sorted(str(tuple(r)) for r in warc.warc_round_trip(spark, frame).collect()) == sorted(map(str, want))
    for archive, block in ((1 << 30, 300), (3000, 1000), (1 << 30, 7)):
        stage = Staging(spark, "test")
        files = warc.write_warc(spark, frame.repartition(2), stage, archive_bytes=archive)
        got = warc.read_warc(spark, files, stage, block_bytes=block if block > 7 else 4096, with_payload=True).collect()
        assert sorted(str((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to)) for r in got) == sorted(map(str, want))
        assert {bytes(r.payload) for r in got if r.record_type == "response"} == {(h or "").encode() for _, _, h, _ in rows}
    assert warc.warc_round_trip(spark, frame.limit(0)).count() == 0
