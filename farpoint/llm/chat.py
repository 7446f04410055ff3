"""Chat formatting by incremental rendering of a template that is only called, never looked into.

The prefixes of a conversation are rendered one after another. If each output continues the one
before, the new part is the span of the new turn; two probe texts in its place show where the text
itself stands in it. A template whose output does not continue rewrites history; its
conversations then give one example for each assistant turn (the prefix that ends there), as
training on the last rendering would show text the model never sees at that point.

Rendering every prefix costs the square of a conversation's length, and its turns are held together. Who knows
that what a turn adds depends on a bounded number of turns before it can say so (``context``): prefixes are then
rendered by their last turns alone, and whole renderings of doubling lengths check the statement.
``chat_digests`` makes no such statement: it renders every prefix whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

Turns = list[tuple[str, str]]
#: Turns that are kept for the renderings of a later part, if a smaller reach is stated: twice as many.
CONTEXT = 16
#: Turns and characters of a conversation in a part.
PART_TURNS, PART_CHARS = 4096, 1 << 23
START, END = "<|im_start|>", "<|im_end|>"
SPANS = "array<struct<role:string,begin:int,stop:int,text_begin:int,text_stop:int,loss:boolean>>"
OUTPUT = f"conv_id long, example int, part int, append_only boolean, formatted string, spans {SPANS}"


def escape(text: str) -> str:
    """Adds a backslash between < and | so that no control string is left; reversible."""
    return re.sub(r"<(\\*)\|", r"<\\\1|", text)


def unescape(text: str) -> str:
    return re.sub(r"<\\(\\*)\|", r"<\1|", text)


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def marked_template(turns: Turns) -> str:
    heads = {role: f"{START}{escape_role(role)}\n" for role in {role for role, _ in turns}}
    return "".join([f"{heads[role]}{escape(text) if '<' in text else text}{END}\n" for role, text in turns])


def parse_marked(formatted: str) -> Turns:
    """The turns of a text that marked_template made."""
    found = re.findall(r"<\|im_start\|>([^\n]*)\n(.*?)<\|im_end\|>\n", formatted, re.S)
    return [(unescape_role(role), unescape(text)) for role, text in found]


def common(a: str, b: str) -> int:
    """Length of the common prefix, by comparing slices."""
    lo, hi = 0, min(len(a), len(b))
    if a[:hi] == b[:hi]:
        return hi
    while lo + 1 < hi:
        mid = (lo + hi) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid
    return lo


def locate(template: Callable[[Turns], str], turns: Turns, context: int | None = None, seen: int = 0) -> tuple[bool, list[tuple[str, list[tuple]]]]:
    """Whether all prefixes only append, and (rendering, spans) of each example.

    The first ``seen`` turns stand before those that are asked for, and are not rendered again.
    Without ``context`` every prefix is rendered. With it, what a turn adds is taken from
    renderings that begin ``context`` turns or more before, and counts only if the parts together are the rendering
    of the whole conversation and of its prefixes of doubling lengths (of a later part: what the rendering of all turns
    held adds to that of the first ``seen``); otherwise every prefix is rendered.
    """
    appends, examples = examined(template, turns, context, seen)
    return appends, list(examples)


def examined(template: Callable[[Turns], str], turns: Turns, context: int | None = None, seen: int = 0) -> tuple[bool, Iterator[tuple[str, list[tuple]]]]:
    """``locate`` with the examples one at a time: those of a rewriting template are as long as all its renderings together."""
    if context is not None and (seen or len(turns) > 2 * context):
        appends, text, spans, _ = _walk(template, turns, context, seen)
        if seen and appends and template(turns) == template(turns[:seen]) + text:
            return appends, iter([(text, spans)])
        if appends and not seen:
            checks = [len(turns), *(1 << i for i in range(len(turns).bit_length()) if 1 << i < len(turns))]
            if all(template(turns[:n]) == text[: spans[n - 1][2]] for n in checks):
                return appends, iter([(text, spans)])
    appends, text, spans, moved = _walk(template, turns, len(turns) + 1, seen)
    if appends:
        return appends, iter([(text, spans)])
    return appends, _renderings(template, turns, [(s[0], *(x - moved for x in s[1:5]), s[5]) for s in spans], seen)


def _renderings(template: Callable[[Turns], str], turns: Turns, spans: list[tuple], seen: int) -> Iterator[tuple[str, list[tuple]]]:
    """The prefixes that end with an assistant turn, or the whole where there is none; spans are places of the turn's own rendering."""
    answers = [i for i, span in enumerate(spans) if span[5]]
    for i in answers:
        yield template(turns[: seen + i + 1]), [spans[i]]
    if not answers:
        yield template(turns), []


def _walk(template: Callable[[Turns], str], turns: Turns, context: int, seen: int = 0) -> tuple[bool, str, list[tuple], int]:
    """Whether renderings append, what they append to that of the ``seen`` turns, the spans in it, and what the last rendering's places were moved by."""
    before, spans, appends = template(turns[:seen]), [], True
    since, moved, parts = 0, -len(before) if seen else 0, [] if seen else [before]  # moved: what stands before the rendered turns
    for n, (role, text) in enumerate(turns[seen:], seen + 1):
        if n - since > 2 * context:
            since = n - 1 - context
            shown, before = moved + len(before), template(turns[since : n - 1])
            moved = shown - len(before)
        now = template(turns[since:n])
        a, b = template([*turns[since : n - 1], (role, "a")]), template([*turns[since : n - 1], (role, "b")])
        begin = len(before) if now.startswith(before) else common(before, now)
        appends &= begin == len(before)
        same = begin if begin == len(before) and a.startswith(before) and b.startswith(before) else 0  # not copied to compare the rest
        at = same + common(a[same:], b[same:])
        stop = len(now) - (len(a) - at - 1)
        if not (len(a) == len(b) and at < len(a) and now.startswith(a[same:at], same) and stop >= at and now.endswith(a[at + 1 :])):
            at = stop = len(now)  # the template does not show this text in one place
        spans.append((role, begin + moved, len(now) + moved, at + moved, stop + moved, role == "assistant"))
        if appends:
            parts.append(now[begin:])
        before = now
    return appends, "".join(parts), spans, moved


def _parts(text: str, spans: list[tuple], cuts: list[int]) -> Iterator[tuple[str, list[tuple]]]:
    """A rendering cut before the turns of these numbers; the spans are places in their part."""
    if not cuts:
        yield text, spans
        return
    for first, last in zip([0, *cuts], [*cuts, len(spans)], strict=True):
        since = spans[first][1] if first else 0
        own = [(role, begin, stop, *((at, end) if at >= since else (stop, stop)), loss) for role, begin, stop, at, end, loss in spans[first:last]]
        yield text[since : spans[last - 1][2]], [(s[0], *(x - since for x in s[1:5]), s[5]) for s in own]


def _format(template: Callable[[Turns], str], part_turns: int, context: int | None):
    names = ["role", "begin", "stop", "text_begin", "text_stop", "loss"]
    kind = pa.list_(pa.struct([("role", pa.string()), *((n, pa.int32()) for n in names[1:5]), ("loss", pa.bool_())]))
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.string(), kind]

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["conv_id", "example", "part", "append_only", "formatted", "spans"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Input sorted by conversation and turn."""
        conv, before, fresh, cuts, chars, part, example, out, held = None, [], [], [], 0, 0, 0, [], 0

        def close() -> Iterator[pa.RecordBatch]:
            nonlocal before, fresh, cuts, chars, part, example, out, held
            appends, examples = examined(template, before + fresh, context, len(before))
            for whole, places in examples:
                for text, spans in _parts(whole, places, cuts if appends else []):
                    out.append((conv, example, part, appends, text, [dict(zip(names, s, strict=True)) for s in spans]))
                    part += appends
                    held += len(text)
                    if held >= PART_CHARS or len(out) >= 2000:
                        yield made(out)
                        out, held = [], 0
                example += not appends
            before, fresh, cuts, chars, part = (before + fresh)[-2 * max(CONTEXT, context or 0) :], [], [], 0, part + (not appends)

        for batch in batches:
            for key, role, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                if key != conv or not (fresh or before):
                    if fresh:
                        yield from close()
                    conv, before, fresh, cuts, chars, part, example = key, [], [], [], 0, 0, 0
                elif len(fresh) - (cuts[-1] if cuts else 0) >= part_turns or chars >= PART_CHARS:
                    if context is None:  # the conversation stays whole until its last turn
                        cuts.append(len(fresh))
                        chars = 0
                    else:
                        yield from close()
                text = text.as_py() or ""
                fresh.append((role or "", text))
                chars += len(text)
        if fresh:
            yield from close()
        yield made(out)

    return run


def format_chats(turns: DataFrame, template: Callable[[Turns], str] = marked_template, part_turns: int = PART_TURNS, context: int | None = None) -> DataFrame:
    """conv_id, example, part, append_only, formatted, spans (in code points of the row; loss marks assistant turns).

    ``context`` is how many turns before it what a turn adds may depend on, where the caller knows; without it every
    prefix is rendered whole, which takes the square of a conversation's length and holds its turns in one task; with it
    turns are read in order and never gathered. Turns are ordered by turn, then role, then text, nulls first; null role or text is empty;
    rows of a null conv_id are one conversation; repeated rows are repeated turns; other columns
    are ignored; an empty table gives none. A conversation of more than ``part_turns`` turns (or PART_CHARS
    characters) whose renderings append comes in parts, whose texts follow one another.
    """
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), "role", "text", "turn")
    ordered = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return ordered.select("conv_id", "role", "text").mapInArrow(_format(template, part_turns, context), OUTPUT)


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Input sorted by conversation, example and part."""
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    at, told, lost, n, loss_chars, chars, out = None, None, None, 0, 0, 0, []

    def done():
        out.append((at[0], n, told.hexdigest(), loss_chars, lost.hexdigest(), chars))

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    for batch in batches:
        for conv, example, text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
            if at != (conv, example):
                if at is not None:
                    done()
                at, told, lost, n, loss_chars, chars = (conv, example), hashlib.sha256(), hashlib.sha256(), 0, 0, 0
            text = text.as_py()
            turns = parse_marked(text)
            loss = "".join(unescape(text[s["text_begin"] : s["text_stop"]]) for s in spans.as_py() if s["loss"])
            told.update("".join(f"{role}\n{body}\n" for role, body in turns).encode())
            lost.update(loss.encode())
            n, loss_chars, chars = n + len(turns), loss_chars + len(loss), chars + len(text)
        yield made(out)
        out = []
    if at is not None:
        done()
    yield made(out)


def chat_digests(spark: SparkSession, turns: DataFrame, part_turns: int = PART_TURNS) -> DataFrame:
    """Writes the formatted conversations, every prefix of them rendered, reads them back and sums each up."""
    written = Staging(spark, "chat").keep(format_chats(turns, part_turns=part_turns), "formatted")
    written = written.repartition("conv_id").sortWithinPartitions("conv_id", "example", "part")
    schema = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    return written.select("conv_id", "example", "formatted", "spans").mapInArrow(_digests, schema)
