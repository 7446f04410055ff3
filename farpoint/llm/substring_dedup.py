"""Repeated passages by prefix-partitioned suffix trees, cut at the window's depth.

All suffixes of all texts would be many times the input. So the texts' suffixes that trees are made of begin where
content says: of the GRAMS[0]-word sequences in a window at that of the smallest hash. Equal windows choose the same
one, and neighbouring windows mostly share it, so a partition, the suffixes of one prefix, gets short
stretches of text around it, each standing for several windows. A partition of one stretch has no internal node and is dropped
before any text moves. The prefix is as long as it has to be: a partition that is too large for a group in
memory is taken apart by the longer sequences, GRAMS[1] words, that its windows choose. Small
partitions are packed into groups, and in a group all suffixes of its stretches are put in order
by ranks of prefixes of 3, 9, 27 words and the window's length: neighbours in this order that agree in the
window's length are the leaves of an internal node of that depth or deeper, a repeat. What even the longer prefix
leaves too large is mostly copies of one passage; it is dealt over several groups, each tells the windows it
holds, once each, and windows that only different groups share are found by content in a second step.
Rows of one text are judged as one: only the first goes through the trees, all lose every window.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

WINDOW = 35
#: Words of a prefix: of all partitions, and of those that are too large. Powers of two.
GRAMS = (8, 16)
#: Partitions with longer prefixes, whose numbers all tasks get (8 bytes each); were there more that are too large, the rest would be dealt as they are.
LONGER = 1_000_000
#: Stretches of a partition that one group takes; each has fewer than 2 * WINDOW words.
GROUP_ROWS = 2000
#: Words put in order at once; three ranks of RANK_BITS bits are packed into one integer.
GROUP_WORDS, RANK_BITS = 1 << 18, 20
#: Words hashed at once.
SCAN_WORDS = 200_000
BROADCAST_SPANS = 200_000
#: Behind the end of any text.
END = (1 << 31) - 1
ODD = np.uint64(0x9E3779B97F4A7C15)
PLACES = "part long, doc_id long, body_hash long, first int, last int"


class _Hashes(dict):
    """64-bit hash of a word, remembered up to a bound."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 200_000:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word, 7)
        return value


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def grams(h: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of ``size`` (a power of two) word hashes."""
    step = 1
    with np.errstate(over="ignore"):
        factor = ODD
        while step < size:
            h = h[:-step] + h[step:] * factor
            factor = factor * factor
            step *= 2
        return _mix(h)


def chosen(h: np.ndarray, size: int, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all sequences of ``size`` words, and for each window the place of the one it chooses."""
    g = grams(h, size)
    low = (g & ~np.uint64(0xFFFFFF)) | np.arange(len(g), dtype=np.uint64)  # ties: the first place
    span, width = window - size + 1, 1
    m = low
    while width * 2 <= span:
        m = np.minimum(m[:-width], m[width:])
        width *= 2
    if span > width:
        m = np.minimum(m[: len(m) - (span - width)], m[span - width :])
    return g, (m & np.uint64(0xFFFFFF)).astype(np.int64)


def stretches(h: np.ndarray, lengths: np.ndarray, window: int = WINDOW, crowded: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """(partition, document, first window, last window) of each run of windows that choose one place.

    ``h`` has the word hashes of the documents one after another, ``lengths`` their words. With ``crowded`` only
    windows of these partitions (sorted) count, and they choose a longer prefix as well.
    """
    none = tuple(np.empty(0, t) for t in (np.uint64, np.int64, np.int64, np.int64))
    if len(h) < window:
        return none
    ends = np.cumsum(lengths)
    g, place = chosen(h, GRAMS[0], window)
    doc = np.repeat(np.arange(len(lengths)), lengths)[: len(place)]
    at = np.flatnonzero(np.arange(len(place)) + window <= ends[doc])
    part = g[place[at]]
    longer = place
    if crowded is not None and len(crowded):
        held = crowded[np.minimum(np.searchsorted(crowded, part), len(crowded) - 1)] == part
        at, part = at[held], part[held]
        g, longer = chosen(h, GRAMS[1], window)
        with np.errstate(over="ignore"):
            part = _mix(part * ODD + g[longer[at]])
    if not len(at):
        return none
    same = (place[at[1:]] == place[at[:-1]]) & (longer[at[1:]] == longer[at[:-1]]) & (at[1:] == at[:-1] + 1) & (doc[at[1:]] == doc[at[:-1]])
    new = np.flatnonzero(np.concatenate([[True], ~same]))
    last = np.concatenate([new[1:], [len(at)]]) - 1
    d = doc[at[new]]
    begin = (ends - lengths)[d]
    return part[new], d, at[new] - begin, at[last] - begin


def _scan(crowded: np.ndarray | None = None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _Hashes()
        for batch in batches:
            ids, keys = batch.column(0), batch.column(1)
            rows, shifts, parts, lengths, held = [], [], [], [], 0

            def flush():
                out = stretches(np.concatenate(parts), np.array(lengths, np.int64), crowded=crowded)
                pick, shift = np.array(rows)[out[1]], np.array(shifts)[out[1]]
                return pa.RecordBatch.from_arrays(
                    [pa.array(out[0].view(np.int64)), ids.take(pa.array(pick)), keys.take(pa.array(pick)), pa.array((out[2] + shift).astype(np.int32)), pa.array((out[3] + shift).astype(np.int32))],
                    names=["part", "doc_id", "body_hash", "first", "last"],
                )

            for i, text in enumerate(batch.column(2)):
                words = (text.as_py() or "").encode("utf-8", "surrogatepass").split()
                if len(words) < WINDOW:
                    continue
                h = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
                del words
                for lo in range(0, len(h) - WINDOW + 1, SCAN_WORDS):  # pieces of a very long text overlap by a window less one
                    piece = h[lo : lo + SCAN_WORDS + WINDOW - 1]
                    rows.append(i)
                    shifts.append(lo)
                    parts.append(piece)
                    lengths.append(len(piece))
                    held += len(piece)
                    if held >= SCAN_WORDS:
                        yield flush()
                        rows, shifts, parts, lengths, held = [], [], [], [], 0
            if held:
                yield flush()

    return run


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, body_hash, text, stretches) -> the text of each stretch."""
    names = ["part", "deal", "deals", "doc_id", "body_hash", "first", "body"]
    for batch in batches:
        offsets = batch.column(3).offsets.to_numpy()
        fields = batch.column(3).values.flatten()
        part, deal, deals = fields[0], fields[1], fields[2]
        first, last = fields[3].to_numpy(), fields[4].to_numpy()
        picks, bodies, held = [], [], 0

        def flush():
            at = np.concatenate([np.arange(offsets[i], offsets[i + 1]) for i in picks])
            doc = pa.array(np.repeat(picks, [offsets[i + 1] - offsets[i] for i in picks]))
            return pa.RecordBatch.from_arrays(
                [part.take(pa.array(at)), deal.take(pa.array(at)), deals.take(pa.array(at)), batch.column(0).take(doc), batch.column(1).take(doc), pa.array(first[at]), pa.array(bodies, pa.binary())], names=names
            )

        for i, text in enumerate(batch.column(2)):
            words = text.as_py().encode("utf-8", "surrogatepass").split()
            bodies += [b" ".join(words[a : b + WINDOW]) for a, b in zip(first[offsets[i] : offsets[i + 1]].tolist(), last[offsets[i] : offsets[i + 1]].tolist(), strict=True)]
            picks.append(i)
            held += len(words)
            if held >= SCAN_WORDS:
                yield flush()
                picks, bodies, held = [], [], 0
        if picks:
            yield flush()


def node_of(ids: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """For each suffix of ``window`` words or more its place in the order of these prefixes (equal ones share a node of that depth), and the nodes' leaf counts.

    Depths 3, 9, 27, ... as far as they go, each from three ranks of the depth before, then the window.
    """
    if len(ids) > 1 << RANK_BITS:
        raise ValueError(f"{len(ids)} words in a group: ranks have {RANK_BITS} bits")
    rank, depth = ids.astype(np.int64), 1
    while depth * 3 <= window:
        packed = (rank[: len(rank) - 2 * depth] << 2 * RANK_BITS) | (rank[depth : len(rank) - depth] << RANK_BITS) | rank[2 * depth :]
        rank = np.unique(packed, return_inverse=True)[1]
        depth *= 3
    if depth < window:
        packed = (rank[: len(rank) - (window - depth)] << 2 * RANK_BITS) | rank[window - depth :]
        if window > 2 * depth:
            middle = (window - depth) // 2
            packed |= rank[middle : middle + len(packed)] << RANK_BITS
        rank = np.unique(packed, return_inverse=True)[1]
    return rank, np.bincount(rank)


def _trees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stretches sorted by group -> spans of repeated words; of dealt-out partitions also their windows."""
    names = ["doc_id", "body_hash", "begin", "stop", "node", "leaves"]
    rows: list[tuple] = []
    fresh: list[tuple] = []
    held, new, group, split = 0, 0, None, False

    def refine(rows, split):
        seen: dict[bytes | int, int] = {}
        pieces, starts, at = [], [], 0
        for i, row in enumerate(rows):
            words = row[6].split(b" ")
            pieces.extend(seen.setdefault(w, len(seen)) for w in words)
            pieces.append(seen.setdefault(i, len(seen)))  # an end of its own, so that no suffix runs on alike
            starts.append(at)
            at += len(words) + 1
        node, leaves = node_of(np.array(pieces))
        starts.append(at)
        out: list[tuple] = []
        told: set[int] = set()
        for row, a, b in zip(rows, starts, starts[1:], strict=False):
            own = node[a : b - WINDOW]
            hit = leaves[own] > 1
            edge = np.flatnonzero(np.diff(np.concatenate([[False], hit, [False]]).astype(np.int8)))
            out += [(row[3], row[4], row[5] + x, row[5] + y - 1 + WINDOW, None, None) for x, y in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True)]
            if split or row[2] > 1:
                words = row[6].split(b" ")
                for j, n in enumerate(own.tolist()):
                    if n not in told:
                        told.add(n)
                        out.append((row[3], row[4], row[5] + j, row[5] + j + WINDOW, hashlib.blake2b(b" ".join(words[j : j + WINDOW]), digest_size=16).digest(), min(int(leaves[n]), 2)))
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.int32()]
        columns = list(zip(*out, strict=True)) or [[]] * 6
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)

    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if (row[0], row[1]) != group:
                if split:
                    yield refine(fresh, True)
                    fresh = []
                elif held + new > GROUP_WORDS and rows:
                    yield refine(rows, False)
                    rows, held = [], 0
                rows += fresh
                held, fresh, new, group, split = held + new if fresh else held, [], 0, (row[0], row[1]), False
            elif new > GROUP_WORDS:  # one key alone is too much, as where rows are repeated: told window by window
                yield refine(fresh, True)
                fresh, new, split = [], 0, True
            fresh.append(row)
            new += row[6].count(b" ") + 2
    if held + new > GROUP_WORDS and rows:
        yield refine(rows, False)
        rows = []
    if split:
        yield refine(fresh, True)
        fresh = []
    if rows + fresh:
        yield refine(rows + fresh, False)


def _beside(stage: Staging, docs: DataFrame, runs: DataFrame, n_runs: int) -> DataFrame:
    """``docs`` that have ``runs`` (doc_id, body_hash, s), with these in an array."""
    per_doc = runs.groupBy("doc_id", "body_hash").agg(F.collect_set("s").alias("runs"))
    per_doc = per_doc.select(F.col("doc_id").alias("k_id"), F.col("body_hash").alias("k_hash"), "runs").hint("broadcast" if n_runs <= BROADCAST_SPANS else "shuffle_hash")
    joined = docs.join(per_doc, docs["doc_id"].eqNullSafe(per_doc["k_id"]) & (docs["body_hash"] == per_doc["k_hash"]))
    return joined.select("doc_id", "body_hash", "text", "runs")


def copies_of(stage: Staging, docs: DataFrame) -> DataFrame:
    """(doc_id, body_hash, again) of rows whose whole text stands more than once; ``again`` on all but one row key of each text."""
    narrow = docs.where(F.length("text") >= 2 * WINDOW - 1).select("doc_id", "body_hash", F.unhex(F.md5("text")).alias("whole"))
    key = F.struct("doc_id", "body_hash")
    groups = stage.keep(narrow.groupBy("whole").agg(F.min(key).alias("first"), F.count("*").alias("n")).where("n > 1"), "wholes")
    copies = narrow.join(groups.hint("merge"), "whole").select("doc_id", "body_hash", (~key.eqNullSafe(F.col("first"))).alias("again"))
    return stage.keep(copies.distinct(), "copies")


def repeated_spans(docs: DataFrame, stage: Staging, group_rows: int = GROUP_ROWS) -> DataFrame:
    """(doc_id, body_hash, spans): word ranges covered by a window that also starts elsewhere."""
    copies = copies_of(stage, docs)
    again = copies.where("again").select(F.col("doc_id").alias("a_id"), F.col("body_hash").alias("a_hash"))
    again = again.hint("broadcast" if again.count() <= BROADCAST_SPANS else "shuffle_hash")

    def placed(crowded: np.ndarray | None, table: str) -> tuple[DataFrame, DataFrame]:
        every = docs.mapInArrow(_scan(crowded), PLACES)
        places = stage.keep(every.join(again, every["doc_id"].eqNullSafe(again["a_id"]) & (every["body_hash"] == again["a_hash"]), "left_anti"), table)
        # written, so that both sides of the join are plain exchanges and a hot partition can be split
        return places, stage.keep(places.groupBy("part").agg(F.count("*").alias("n")).where("n > 1"), f"{table}-sizes")

    def fitting(places: DataFrame, sizes: DataFrame) -> DataFrame:
        deals = F.ceil(F.col("n") / group_rows).cast("int")
        fits = places.join(sizes.select("part", deals.alias("deals")).hint("merge"), "part")
        deal = F.pmod(F.xxhash64("doc_id", "body_hash", "first"), F.col("deals")).cast("int")
        return fits.select("doc_id", "body_hash", F.struct("part", deal.alias("deal"), "deals", "first", "last").alias("s"))

    places, sizes = placed(None, "places")
    large = sizes.where(F.col("n") > group_rows).orderBy(F.desc("n"), "part").limit(LONGER)
    crowded = np.sort(large.select("part").toArrow().column(0).to_numpy().view(np.uint64))
    if len(crowded):
        longer = stage.keep(large.select("part"), "longer")
        kept = fitting(places, sizes.join(longer, "part", "left_anti")).unionByName(fitting(*placed(crowded, "longer-places")))
    else:
        kept = fitting(places, sizes)
    kept = stage.keep(kept, "runs")
    texts = _beside(stage, docs, kept, kept.count()).mapInArrow(_texts, "part long, deal int, deals int, doc_id long, body_hash long, first int, body binary")
    groups = texts.repartition("part", "deal").sortWithinPartitions("part", "deal")
    found = stage.keep(groups.mapInArrow(_trees, "doc_id long, body_hash long, begin int, stop int, node binary, leaves int"), "nodes")
    split = found.where("node is not null")
    wide = split.groupBy("node").agg(F.sum("leaves").alias("all_leaves")).where("all_leaves > 1")
    spans = found.where("node is null").unionByName(split.where("leaves = 1").join(wide.hint("merge"), "node", "left_semi").select(found.columns))
    spans = spans.select("doc_id", "body_hash", "begin", "stop").unionByName(copies.select("doc_id", "body_hash", F.lit(0).alias("begin"), F.lit(END).alias("stop")))
    per_doc = spans.groupBy("doc_id", "body_hash").agg(F.collect_list(F.struct("begin", "stop")).alias("spans"))
    return per_doc.mapInArrow(_merge, "doc_id long, body_hash long, spans array<struct<begin:int,stop:int>>")


def merged(begin: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Overlapping and touching spans as one."""
    order = np.argsort(begin, kind="stable")
    begin, reach = begin[order], np.maximum.accumulate(stop[order])
    new = np.flatnonzero(np.concatenate([[True], begin[1:] > reach[:-1]]))
    return begin[new], reach[np.concatenate([new[1:], [len(begin)]]) - 1]


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        offsets = batch.column(2).offsets.to_numpy()
        begin, stop = (c.to_numpy() for c in batch.column(2).values.flatten())
        pairs = [merged(begin[a:b], stop[a:b]) for a, b in zip(offsets, offsets[1:], strict=False)]
        cuts = pa.array(np.concatenate([[0], np.cumsum([len(b) for b, _ in pairs])]).astype(np.int32))
        both = [np.concatenate([p[i] for p in pairs]) if pairs else np.empty(0, np.int32) for i in (0, 1)]
        spans = pa.ListArray.from_arrays(cuts, pa.StructArray.from_arrays([pa.array(x.astype(np.int32)) for x in both], ["begin", "stop"]))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), spans], names=["doc_id", "body_hash", "spans"])


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: list[list] = [[], [], []]
        for text, spans in zip(batch.column(1), batch.column(2), strict=True):
            words = (text.as_py() or "").encode("utf-8", "surrogatepass").split()
            n, gone = len(words), 0
            if spans.is_valid and n >= WINDOW:  # a copied text may be shorter
                drop = np.zeros(n + 1, np.int32)
                edges = spans.values.flatten()
                np.add.at(drop, edges[0].to_numpy(), 1)
                np.add.at(drop, np.minimum(edges[1].to_numpy(), n), -1)
                stay = np.cumsum(drop)[:n] == 0
                gone = n - int(stay.sum())
                words = [words[i] for i in np.flatnonzero(stay).tolist()]
            for column, v in zip(out, (n, gone, b" ".join(words).decode("utf-8", "surrogatepass")), strict=True):
                column.append(v)
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v, k) for v, k in zip(out, [pa.int64(), pa.int64(), pa.string()], strict=True))], names=["doc_id", "n_words", "n_removed", "kept_text"])


def substring_dedup(spark: SparkSession, docs: DataFrame, group_rows: int = GROUP_ROWS) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_text (kept words with single spaces).

    A word goes if a window of WINDOW words over it starts anywhere else too, same document
    included; a text that stands twice in the table loses all windows in both rows. Null text has no
    words, shorter texts than a window lose none, an empty table gives none; other columns are ignored.
    """
    stage = Staging(spark, "substrings")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("body_hash"), "text")
    with stage.scratch() as tmp:
        spans = stage.keep(repeated_spans(docs, tmp, group_rows), "spans")
    total = spans.agg(F.coalesce(F.sum(F.size("spans")), F.lit(0))).first()[0]
    side = spans.select(F.col("doc_id").alias("s_id"), F.col("body_hash").alias("s_hash"), "spans").hint("broadcast" if total <= BROADCAST_SPANS else "shuffle_hash")
    joined = docs.join(side, docs["doc_id"].eqNullSafe(side["s_id"]) & (docs["body_hash"] == side["s_hash"]), "left")
    return joined.select("doc_id", "text", "spans").mapInArrow(_cut, "doc_id long, n_words long, n_removed long, kept_text string")
