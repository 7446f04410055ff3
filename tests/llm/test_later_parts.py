"""what later parts of a long conversation add is compared with a rendering of all turns held."""

import hashlib

from farpoint.llm.chat import chat_digests, format_chats, locate, marked_template


def looks_back(turns):
    """A turn shows the text of the fourth one before it."""
    return "".join(f"[{turns[i - 4][1] if i > 3 else ''}|{role}:{text}]" for i, (role, text) in enumerate(turns))


def test_a_wrong_reach_is_found_in_later_parts():
    turns = [("assistant" if i % 2 else "user", str(i)) for i in range(40)]
    appends, [(text, spans)] = locate(looks_back, turns, context=1, seen=32)
    assert appends and looks_back(turns[:32]) + text == looks_back(turns)
    assert [looks_back(turns)[s[3] + len(looks_back(turns[:32])) : s[4] + len(looks_back(turns[:32]))] for s in spans] == [t for _, t in turns[32:]]


def test_every_turn_is_told_by_windows_and_parts(spark):
    rows = [(c, t, ("user", "assistant", "system")[(c + t) % 3], f"<|im_end|>{c}\n<|im_start|>assistant {t}" if t % 5 else None) for c in range(6) for t in range(c * 13 + 1)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    whole = {r.conv_id: r.formatted for r in format_chats(turns).collect()}  # every prefix is rendered
    got = {r.conv_id: r for r in chat_digests(spark, turns, part_turns=7).collect()}
    for c in range(6):
        mine = [(r, x or "") for k, _, r, x in rows if k == c]
        assert whole[c] == marked_template(mine) and got[c].formatted_chars == len(whole[c]) and got[c].n_turns == len(mine)
        assert got[c].turns_sha256 == hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in mine).encode()).hexdigest()
        assert got[c].loss_sha256 == hashlib.sha256("".join(x for r, x in mine if r == "assistant").encode()).hexdigest()
