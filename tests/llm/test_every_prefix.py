"""op4 renders every prefix of every conversation, also of those that come in parts."""

import functools
import uuid

from farpoint.llm import chat


def rows_of(sizes):
    return [(c, t, ("user", "assistant", "system")[(c + t) % 3], f"{c}<|{t}" if t % 4 else None) for c, n in sizes.items() for t in range(n)]


def test_digests_render_every_prefix(spark, tmp_path, monkeypatch):
    rows = rows_of({1: 3, 2: 23, 3: 40})
    seen = str(tmp_path)

    def noted(turns):
        with open(f"{seen}/{uuid.uuid4().hex}", "w") as f:
            f.write(repr(turns))
        return chat.marked_template(turns)

    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    monkeypatch.setattr(chat, "format_chats", functools.partial(chat.format_chats, template=noted))
    assert {r.conv_id: r.n_turns for r in chat.chat_digests(spark, frame, part_turns=7).collect()} == {1: 3, 2: 23, 3: 40}
    rendered = {f.read_text() for f in tmp_path.iterdir()}
    for c in (1, 2, 3):
        turns = [(r, x or "") for k, _, r, x in rows if k == c]
        for n in range(1, len(turns) + 1):
            assert repr(turns[:n]) in rendered
            assert all(repr([*turns[: n - 1], (turns[n - 1][0], probe)]) in rendered for probe in "ab")


def test_history_rewritten_in_a_later_part(spark):
    def hides_first(turns):
        """The first turn goes from sight when the last one is the 31st."""
        return chat.marked_template(turns[1:] if len(turns) == 31 else turns)

    rows = rows_of({1: 3, 3: 40})
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = chat.format_chats(frame, hides_first, part_turns=7).orderBy("conv_id", "example").collect()
    assert [r.append_only for r in got if r.conv_id == 1] == [True]
    turns = [(r, x or "") for k, _, r, x in rows if k == 3]
    answers = [i for i, (r, _) in enumerate(turns) if r == "assistant"]
    mine = [r for r in got if r.conv_id == 3]
    assert [r.formatted for r in mine] == [hides_first(turns[: i + 1]) for i in answers] and not any(r.append_only for r in mine)
    assert [chat.unescape(r.formatted[r.spans[0].text_begin : r.spans[0].text_stop]) for r in mine] == [turns[i][1] for i in answers]


def test_spans_of_parts(spark):
    rows = rows_of({3: 40, 5: 7, 6: 8})
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    for template in (chat.marked_template, lambda turns: "<s>" + chat.marked_template(turns)):
        got = chat.format_chats(frame, template, part_turns=7).orderBy("conv_id", "part").collect()
        assert [(r.conv_id, r.part) for r in got] == [*((3, p) for p in range(6)), (5, 0), (6, 0), (6, 1)] and all(r.append_only for r in got)
        for c in (3, 5, 6):
            turns, parts = [(r, x or "") for k, _, r, x in rows if k == c], [r for r in got if r.conv_id == c]
            assert "".join(r.formatted for r in parts) == template(turns)
            assert [(s.role, chat.unescape(r.formatted[s.text_begin : s.text_stop])) for r in parts for s in r.spans] == turns
            assert all(chat.marked_template([t]) == r.formatted[s.begin : s.stop] for t, (r, s) in zip(turns, ((r, s) for r in parts for s in r.spans), strict=True))
