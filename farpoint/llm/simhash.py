"""SimHash near-duplicate detection with a pigeonring candidate filter.

Fingerprints of 64 bits are cut into a ring of segments. If two differ in at most ``limit`` bits, the
ring principle gives a segment from which every chain of l consecutive segments has at most l * limit /
segments differing bits. The chains too short to allow one bit are therefore equal and serve as the
join key; the longer chains prune candidates before the full Hamming distance. The bits outside the key
form a ring of their own with the same limit, so a key that too many fingerprints share is split by an equal
chain of that ring, and so on until a key leaves FREE_BITS bits or fewer, which bounds what can share it.
Copies share a fingerprint and are collapsed before; a bucket gives links to a root of each linked set
in it, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging, text_hash, without_rows
from farpoint.llm.components import connected_components
from farpoint.llm.shingles import SEED, majority_bits, shingle_hashes
from farpoint.llm.similar import similar_links, slot_counts, with_prints

SEGMENTS = 8
LIMIT = 2
#: Fingerprints that a bucket compares; a key that more share is split by the next ring.
HEAVY = 1024
#: Bits that the last ring leaves open.
FREE_BITS = 9


def fingerprint(text: str | None, shingle: int = 3, seed: int = SEED) -> int:
    """A bit is 1 if it is set in over half of the XXH64 of the word shingles, repeats included."""
    return majority_bits(shingle_hashes(text, shingle, seed))


def with_fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = np.fromiter((fingerprint(x.as_py(), shingle) for x in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, fp long")


def equal_chain(segments: int, limit: int) -> int:
    """The longest chain whose budget is below one bit."""
    return max(n for n in range(segments + 1) if n * limit < segments)


def ring_levels(limit: int = LIMIT) -> list[tuple[int, int, int]]:
    """(bits, bits of a segment, segments of an equal chain) of each ring: first the fingerprint's, then those of what is left."""
    if not 0 < limit < 2 * SEGMENTS:
        raise ValueError(f"limit {limit}: ring keys are made for 1 to {2 * SEGMENTS - 1} bits")
    levels, bits = [], 64
    while bits > FREE_BITS and len(levels) < 14:  # four bits of a path for each
        width = next((w for w in (64 // SEGMENTS, 4, 2, 1) if bits % w == 0 and equal_chain(bits // w, limit)), 0)
        if not width:
            break
        levels.append((bits, width, equal_chain(bits // width, limit)))
        bits -= width * levels[-1][2]
    return levels


def with_ring_keys(rows: DataFrame, bits: int, width: int, chain: int) -> DataFrame:
    """(fp, path, same, rest) -> a row for each start on the ring of ``rest``: the starts so far, the bits that must be equal, the bits left."""
    held, each = width * chain, []
    for i in range(bits // width):
        back = F.shiftleft("rest", bits - i * width)
        turned = F.shiftrightunsigned("rest", i * width).bitwiseOR(back if bits == 64 else back.bitwiseAND(F.lit((1 << bits) - 1))) if i else F.col("rest")
        same = F.shiftleft("same", held).bitwiseOR(turned.bitwiseAND(F.lit((1 << held) - 1)))
        each.append(F.struct((F.shiftleft("path", 4) + i).alias("path"), same.alias("same"), F.shiftrightunsigned(turned, held).alias("rest")))
    return rows.select("fp", F.inline(F.array(*each)))


def chain_passes(diff: np.ndarray, start: np.ndarray, segments: int = SEGMENTS, limit: int = LIMIT) -> np.ndarray:
    """Whether all chains from the start segment keep to their budgets; the last is the full distance."""
    width = 64 // segments
    shift = (start * width).astype(np.uint64)
    turned = np.where(shift == 0, diff, (diff >> shift) | (diff << ((np.uint64(64) - shift) & np.uint64(63))))
    ok = np.ones(len(diff), bool)
    for n in range(1, segments + 1):
        mask = np.uint64((1 << n * width) - 1)
        ok &= np.bitwise_count(turned & mask).astype(np.int64) * segments <= n * limit
    return ok


def link_sorted(run: np.ndarray, start: np.ndarray, fp: np.ndarray, limit: int = LIMIT) -> tuple[np.ndarray, np.ndarray]:
    """Links (fingerprint, root) inside runs of equal numbers; at most one for each row."""
    left, right = [], []
    live, gap = np.arange(len(run) - 1), 1
    while len(live):
        live = live[live + gap < len(run)]
        live = live[run[live] == run[live + gap]]
        ok = chain_passes(fp[live] ^ fp[live + gap], start[live], limit=limit)
        left.append(live[ok])
        right.append(live[ok] + gap)
        gap += 1
    if not left:
        return fp[:0], fp[:0]
    i, j, label = np.concatenate(left), np.concatenate(right), np.arange(len(run))
    while len(i):
        low = np.minimum(label[i], label[j])
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        label = label[label]
        if (label[i] == label[j]).all():
            break
    own = np.flatnonzero(label != np.arange(len(run)))
    return fp[own], fp[label[own]]


def _bucket_links(level: int, limit: int):
    """Input (path, same, fp) sorted by path and same; a run that a batch ends with waits for the next."""

    def linked(path, same, fp):
        run = np.cumsum(np.concatenate([[True], (path[1:] != path[:-1]) | (same[1:] != same[:-1])]))
        a, b = link_sorted(run, path >> (4 * level), fp, limit)
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.uint64)]
        for batch in batches:
            new = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            held = [np.concatenate([x, y.view(x.dtype)]) for x, y in zip(held, new, strict=True)]
            path, same, _ = held
            last = np.flatnonzero((path != path[-1]) | (same != same[-1])) if len(path) else path
            if len(last):
                cut = int(last[-1]) + 1
                yield linked(*(x[:cut] for x in held))
                held = [x[cut:] for x in held]
        if len(held[0]):
            yield linked(*held)

    return run


def near_links(stage: Staging, prints: DataFrame, heavy: int = HEAVY, limit: int = LIMIT) -> DataFrame:
    """Distinct fingerprints (fp) -> links (a, b) that span every set reachable over <= ``limit`` bits."""
    rows = prints.select("fp", F.lit(0).cast("long").alias("path"), F.lit(0).cast("long").alias("same"), F.col("fp").alias("rest"))
    links, levels = None, ring_levels(limit)
    for level, (bits, width, chain) in enumerate(levels):
        keyed = with_ring_keys(rows, bits, width, chain)
        sizes = stage.keep(keyed.groupBy("path", "same").agg(F.count("*").alias("n")).where("n > 1"), "sizes")
        crowded = F.col("n") > heavy if level + 1 < len(levels) else F.lit(False)
        light = keyed.join(sizes.where(~crowded).select("path", "same"), ["path", "same"]).select("path", "same", "fp")
        found = light.repartition("path", "same").sortWithinPartitions("path", "same").mapInArrow(_bucket_links(level, limit), "a long, b long")
        links = found if links is None else links.unionByName(found)
        if level + 1 == len(levels) or sizes.where(crowded).isEmpty():
            break
        rows = stage.keep(keyed.join(sizes.where(crowded).select("path", "same"), ["path", "same"]).select("fp", "path", "same", "rest"), "crowded")
    return links


def simhash_groups(spark: SparkSession, docs: DataFrame, heavy: int = HEAVY, shingle: int = 3, limit: int = LIMIT) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id.

    Null and word-less texts have fingerprint zero and link like any other. component_id is the
    smallest doc_id reachable over links of ``limit`` bits or fewer (null ids are passed over unless a
    group has no other). Repeated rows each get a row; other columns are ignored.
    """
    stage = Staging(spark, "simhash")
    prints = stage.keep(with_fingerprints(docs, shingle), "prints")
    with stage.scratch() as tmp:
        nodes = tmp.keep(prints.groupBy("fp").agg(F.min("doc_id").alias("low")), "nodes")
        roots = connected_components(tmp, near_links(tmp, nodes.select("fp"), heavy, limit))
        placed = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", F.coalesce("root", "fp").alias("root"))
        lows = placed.groupBy("root").agg(F.min("low").alias("component_id"))
        named = stage.keep(placed.join(lows, "root").select("fp", "component_id"), "named")
    return prints.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """One document of each group stays: that with the smallest id (nulls last), of one id the smallest text
    hash, once if its row is repeated. Rows count as repeated where id and text are equal; a row
    without words also where its id stands on a row with words (a repeat that line dedup has emptied).

    Groups hold what is reachable over fingerprints of 5-word shingles LIMIT bits or fewer apart, as in
    simhash_groups, or a Jaccard similarity of these shingles of 0.8 or more.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = rows.withColumn("text_hash", text_hash())
    stage = Staging(spark, "near")
    with stage.scratch() as tmp:
        prints = tmp.keep(with_prints(rows, slot_counts(rows)), "prints")
        with tmp.scratch() as inner:
            links = tmp.keep(similar_links(inner, rows, prints, near_links(inner, prints.select("fp").distinct())), "links")
        roots = connected_components(tmp, links)
        emptied = prints.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max(F.col("n_items") > 0).alias("held"), F.min("n_items").alias("n")).where("held AND n = 0")
        again = prints.where("n_items = 0").select("doc_id", "text_hash").join(emptied, "doc_id", "left_semi").distinct()
        placed = prints.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("doc_id", "text_hash", "n_items", F.coalesce("root", "fp").alias("root"))
        placed = tmp.keep(placed.join(emptied.select("doc_id", "held"), "doc_id", "left").where("n_items > 0 OR held IS NULL").drop("held"), "placed")
        key = F.struct(F.col("doc_id").isNull(), "doc_id", "text_hash")
        firsts = tmp.keep(placed.groupBy("root").agg(F.min(key).alias("first")).select(F.col("first.doc_id").alias("f_id"), F.col("first.text_hash").alias("f_hash")), "firsts").hint("merge")
        stays = placed["doc_id"].eqNullSafe(firsts["f_id"]) & placed["text_hash"].eqNullSafe(firsts["f_hash"])  # by row, as one root may have a third of them
        gone = placed.join(firsts, stays, "left_anti").select("doc_id", "text_hash").union(again)
        left = without_rows(stage, docs, gone)
        repeated = not placed.join(firsts, stays, "left_semi").groupBy("doc_id", "text_hash").agg(F.count("*").alias("n")).where("n > 1").isEmpty()
    return left.withColumn("__hash", text_hash()).dropDuplicates(["doc_id", "__hash"]).drop("__hash") if repeated else left
