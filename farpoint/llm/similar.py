"""Texts whose sets of word shingles have a Jaccard similarity of 0.8 or more, by a prefix-filtered join.

The shingles of a text are put in one order for all texts, rare ones first. Two similar texts share one of
the first few of each, so these are the join key; sizes, and how many of the first shingles two texts have to share at
least, prune, and whole sets decide. A key that more than
CROWD texts share is replaced by keys of one shingle more, for similar texts share almost all of them.
Inside a key pairs are not written out: first each text is compared with one hub of its size, what is
found similar is joined to components, and only texts of different components are then compared with one another.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.llm.common import Staging
from farpoint.llm.components import connected_components
from farpoint.llm.shingles import majority_bits, shingle_hashes

#: Words of a shingle.
SHINGLE = 5
#: Texts that a key compares with one another; the shingles that a key has at most.
CROWD, LEVELS = 1024, 3
#: Counts of shingles are kept for so many classes of them.
SLOTS = 1 << 16
#: Members of a hub that one task compares with it.
HUB_ROWS = 1000
BROADCAST_ROWS = 100_000
PRINT = "doc_id long, text_hash binary, fp long, n_items long, set_hash binary, prefix array<long>"


def slot_counts(rows: DataFrame) -> np.ndarray:
    """How often shingles of each class stand in all texts. The order needs no more: it is exact for any counts, only its speed depends on them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(SLOTS, np.int64)
        for batch in batches:
            for text in batch.column(0):
                for hashes in shingle_hashes(text.as_py(), SHINGLE):
                    held += np.bincount((hashes % np.uint64(SLOTS)).astype(np.int64), minlength=SLOTS)
        found = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), pa.array(held[found])], names=["slot", "n"])

    counts = np.zeros(SLOTS, np.int64)
    for r in rows.select("text").mapInArrow(run, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).collect():  # SLOTS rows at most
        counts[r.slot] = r.n
    return counts


def prefix_size(n: int) -> int:
    """Of the first so many of n items, in one order for all sets, two sets of Jaccard 0.8 or more share one."""
    return n - (4 * n + 4) // 5 + 1 if n else 0


def with_prints(rows: DataFrame, counts: np.ndarray) -> DataFrame:
    """(doc_id, text, text_hash) -> PRINT: fingerprint, size and hash of the set of shingles, and its first items in the order."""
    sent = rows.sparkSession.sparkContext.broadcast(counts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = sent.value
        for batch in batches:
            prints, sizes, hashes, prefixes = [], [], [], []
            for text in (x.as_py() for x in batch.column(1)):
                pieces = list(shingle_hashes(text, SHINGLE))
                items = np.unique(np.concatenate([np.empty(0, np.uint64), *pieces]))
                keep = min(prefix_size(len(items)) + LEVELS - 1, len(items))
                rarity = counts[(items % np.uint64(SLOTS)).astype(np.int64)]
                prints.append(majority_bits(pieces))
                sizes.append(len(items))
                hashes.append(hashlib.blake2b(items.tobytes(), digest_size=16).digest())
                prefixes.append(items[np.argsort(rarity, kind="stable")[:keep]].view(np.int64))
            fp = pa.array(np.array(prints, np.uint64).view(np.int64))
            columns = [batch.column(0), batch.column(2), fp, pa.array(sizes, pa.int64()), pa.array(hashes, pa.binary()), pa.array(prefixes, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "text_hash", "fp", "n_items", "set_hash", "prefix"])

    return rows.select("doc_id", "text", "text_hash").mapInArrow(run, PRINT)


def shared_keys(stage: Staging, texts: DataFrame) -> list[tuple[int, DataFrame]]:
    """(shingles of a key, rows (key, tid, n_at) of the keys that several texts share) for each length of keys. n_at has the set's size and the place of the key's last shingle."""
    last = F.col("n_items") - F.ceil(F.col("n_items") * 4 / 5)  # the last place of a prefix
    n_at = F.shiftleft(F.col("n_items").cast("long"), 32)
    rows, out = texts.select("tid", "n_items", F.posexplode("prefix").alias("at", "key")).where(F.col("at") <= last).select("key", "tid", (n_at + F.col("at")).alias("n_at")), []
    for level in range(1, LEVELS + 1):
        sizes = rows.groupBy("key").agg(F.count("*").alias("members")).where("members > 1")
        sizes = stage.keep(sizes, "sizes")  # written, so that both sides of the join are plain exchanges and a hot key can be split
        shared = stage.keep(rows.join(sizes.hint("merge"), "key"), "shared")
        crowded = F.col("members") > CROWD if level < LEVELS else F.lit(False)
        light = shared.where(~crowded).select("key", "tid", "n_at")
        n_crowded = sizes.where(crowded).agg(F.coalesce(F.sum("members"), F.lit(0))).first()[0]
        out.append((level, light))
        if level == LEVELS or not n_crowded:
            break
        begun = shared.where(crowded).groupBy("tid").agg(F.collect_list(F.struct("key", "n_at")).alias("begun"))  # at most the prefix's size each
        begun = F.broadcast(begun) if n_crowded <= BROADCAST_ROWS else begun.hint("merge")
        more = texts.join(begun, "tid").select("tid", "n_items", "prefix", F.explode("begun").alias("b")).select("tid", "n_items", "b", F.posexplode("prefix").alias("next", "item"))
        more = more.where((F.col("next") > F.col("b.n_at").bitwiseAND(F.lit((1 << 32) - 1))) & (F.col("next") <= last + level))
        rows = stage.keep(more.select(F.xxhash64("b.key", "item").alias("key"), "tid", (n_at + F.col("next")).alias("n_at")), "longer")
    return out


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables of whole runs of equal values in the first column; the input is sorted by it."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        key = batch.column(0).to_numpy()
        other = np.flatnonzero(key != key[-1])
        cut = int(other[-1]) + 1 if len(other) else 0
        if held and (cut or held[-1].column(0)[-1] != batch.column(0)[0]):
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            held = []
        elif cut:
            yield pa.Table.from_batches([batch.slice(0, cut)])
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held)


def possible(n: np.ndarray, at: np.ndarray, a: np.ndarray, b: np.ndarray, level: int) -> np.ndarray:
    """Whether sizes and places of the pairs allow a Jaccard of 0.8, if the key's last item is the level-th common one."""
    most = np.minimum(n[a] - at[a], n[b] - at[b]) + level - 1
    return 9 * most >= 4 * (n[a] + n[b])


def hub_pairs(key: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows sorted by key and n -> each row with the hub of its key and size: the first row, then the first that is too large for the hub."""
    first = np.concatenate([[True], key[1:] != key[:-1]])
    hub = np.maximum.accumulate(np.where(first, np.arange(len(key)), 0))
    while True:
        far = 4 * n > 5 * n[hub]
        if not far.any():
            break
        # of each hub the first row that is too large is the next hub, for all rows behind it that had this one
        old = hub[far]
        lead = np.flatnonzero(far)[np.concatenate([[True], old[1:] != old[:-1]])]
        hub[far] = lead[np.searchsorted(hub[lead], old)]
    a = np.flatnonzero(hub != np.arange(len(key)))
    return a, hub[a]


def cross_pairs(key: np.ndarray, n: np.ndarray, root: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows sorted by key and n -> the pairs of one key but different components that sizes allow."""
    left, right = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
    starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.empty(0, np.int64)
    one = np.minimum.reduceat(root, starts) == np.maximum.reduceat(root, starts) if len(key) else starts
    live, gap = np.flatnonzero(~np.repeat(one, np.diff(np.append(starts, len(key))))), 1
    while len(live):
        live = live[live + gap < len(key)]
        live = live[(key[live] == key[live + gap]) & (5 * n[live] >= 4 * n[live + gap])]  # sorted by size: a later row is too large as well
        apart = live[root[live] != root[live + gap]]
        left.append(apart)
        right.append(apart + gap)
        gap += 1
    return np.concatenate(left), np.concatenate(right)


def _pairs(level: int, crossing: bool):
    """(key, tid, n_at[, root]) sorted by key and n_at -> pairs (a, b) of tids that sizes and places allow."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _runs(batches):
            key, tid, n_at, *root = (c.to_numpy() for c in rows.columns)
            n, at = n_at >> 32, n_at & 0xFFFFFFFF
            a, b = cross_pairs(key, n, *root) if crossing else hub_pairs(key, n)
            ok = possible(n, at, a, b, level)
            a, b = a[ok], b[ok]
            swap = (n[a] < n[b]) | ((n[a] == n[b]) & (tid[a] < tid[b]))  # b is the smaller set, as a hub is
            a, b = tid[np.where(swap, b, a)], tid[np.where(swap, a, b)]
            for lo in range(0, len(a), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + 100_000]) for x in (a, b)], names=["a", "b"])

    return run


def candidates(stage: Staging, keys: list[tuple[int, DataFrame]], texts: DataFrame, roots: DataFrame | None) -> DataFrame:
    """Distinct pairs (a, b) to be compared: with hubs, or where ``roots`` (tid, smallest tid of its component) are given, across components.

    One of two prefixes ends first in the order, and what is behind it counts once at most; so many items of
    both prefixes have to be common, or the sets are not similar.
    """
    out = None
    for level, rows in keys:
        if roots is not None:
            rows = rows.join(roots.hint("merge"), "tid", "left").select("key", "tid", "n_at", F.coalesce("root", "tid").alias("root"))
        dealt = rows.repartition("key").sortWithinPartitions("key", "n_at", "tid")
        found = dealt.mapInArrow(_pairs(level, roots is not None), "a long, b long")
        out = found if out is None else out.unionByName(found)
    met = stage.keep(out.distinct(), "met")
    behind = F.ceil(F.col("n_items") * 4 / 5) - 1
    prefix = F.slice("prefix", 1, (F.col("n_items") - behind).cast("int"))
    for side in ("a", "b"):
        met = met.join(texts.select(F.col("tid").alias(side), F.col("n_items").alias(f"n_{side}"), behind.alias(f"behind_{side}"), prefix.alias(f"prefix_{side}")).hint("merge"), side)
    least = F.ceil((F.col("n_a") + F.col("n_b")) * 4 / 9) - F.greatest("behind_a", "behind_b")
    return stage.keep(met.where(F.size(F.array_intersect("prefix_a", "prefix_b")) >= least).select("a", "b"), "pairs")


def _whole_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(tid, text, roles) -> the set of the text's shingles for each role (hub, part, member)."""
    names = ["hub", "part", "member", "tid", "items"]
    for batch in batches:
        for tid, text, roles in zip(batch.column(0), batch.column(1), batch.column(2).to_pylist(), strict=True):
            items = np.unique(np.concatenate([np.empty(0, np.uint64), *shingle_hashes(text.as_py(), SHINGLE)])).view(np.int64)
            step = max(1, 500_000 // max(1, len(items)))
            for lo in range(0, len(roles), step):
                some = roles[lo : lo + step]
                columns = [pa.array([r[k] for r in some], t) for k, t in (("hub", pa.int64()), ("part", pa.int32()), ("member", pa.bool_()))]
                yield pa.RecordBatch.from_arrays([*columns, pa.array([tid.as_py()] * len(some), pa.int64()), pa.array([items] * len(some), pa.list_(pa.int64()))], names=names)


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted by hub, part and member: the hub's set comes first, then those that are compared with it."""
    hub, held = None, np.empty(0, np.int64)
    for batch in batches:
        out = []
        for key, part, member, tid, items in zip(*(batch.column(i) for i in range(5)), strict=True):
            items = items.values.to_numpy()
            if not member.as_py():
                hub, held = key.as_py(), items
            elif key.as_py() == hub and 9 * len(np.intersect1d(held, items, assume_unique=True)) >= 4 * (len(held) + len(items)):
                out.append((tid.as_py(), hub))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in (0, 1)], names=["a", "b"])


def similar_of(stage: Staging, rows: DataFrame, texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """Of the pairs (a, b) those whose whole sets are similar. A hub's set goes once to each part of its members, a member's once for each pair."""
    hubs = pairs.groupBy("b").agg(F.ceil(F.count("*") / HUB_ROWS).cast("int").alias("parts"))
    hubs = stage.keep(hubs.withColumnRenamed("b", "hub"), "hubs")
    part = F.pmod(F.xxhash64("a"), F.col("parts")).cast("int")
    members = pairs.withColumnRenamed("b", "hub").join(hubs.hint("merge"), "hub").select(F.col("a").alias("tid"), F.struct("hub", part.alias("part"), F.lit(True).alias("member")).alias("role"))
    own = hubs.select(F.col("hub").alias("tid"), "hub", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
    roles = members.unionByName(own.select("tid", F.struct("hub", "part", F.lit(False).alias("member")).alias("role")))
    todo = stage.keep(roles.groupBy("tid").agg(F.collect_list("role").alias("roles")).join(texts.select("tid", F.col("doc_id").alias("k_id"), F.col("text_hash").alias("k_hash")).hint("merge"), "tid"), "roles")
    n_roles = todo.agg(F.coalesce(F.sum(F.size("roles")), F.lit(0))).first()[0]
    side = F.broadcast(todo) if n_roles <= BROADCAST_ROWS else todo
    wanted = rows.join(side, rows["doc_id"].eqNullSafe(side["k_id"]) & rows["text_hash"].eqNullSafe(side["k_hash"]))
    sets = wanted.select("tid", "text", "roles").mapInArrow(_whole_sets, "hub long, part int, member boolean, tid long, items array<long>")
    dealt = sets.repartition("hub", "part").sortWithinPartitions("hub", "part", "member")
    return stage.keep(dealt.mapInArrow(_compared, "a long, b long"), "similar")


def similar_links(stage: Staging, rows: DataFrame, prints: DataFrame, others: DataFrame) -> DataFrame:
    """Links (a, b) between fingerprints that, with the links ``others``, connect all texts of Jaccard 0.8 or more. Rows of one set of shingles are linked as well."""
    key = F.struct(F.col("doc_id").isNull(), "doc_id", "text_hash")
    groups = prints.where("n_items > 0").groupBy("set_hash").agg(F.min(key).alias("first"), F.min("fp").alias("fp"), F.first("n_items").alias("n_items"), F.first("prefix").alias("prefix"))
    texts = stage.keep(groups.select(F.monotonically_increasing_id().alias("tid"), "set_hash", "first.doc_id", "first.text_hash", "fp", "n_items", "prefix"), "texts")
    held = texts.select("set_hash", F.col("fp").alias("b"))
    links = stage.keep(prints.where("n_items > 0").select("set_hash", F.col("fp").alias("a")).distinct().join(held.hint("merge"), "set_hash").where("a <> b").select("a", "b").unionByName(others), "links")
    keys = shared_keys(stage, texts)
    numbers = texts.select("tid", "fp")

    def between(pairs: DataFrame) -> DataFrame:
        named = pairs.join(numbers.select(F.col("tid").alias("a"), F.col("fp").alias("fa")).hint("merge"), "a").join(numbers.select(F.col("tid").alias("b"), F.col("fp").alias("fb")).hint("merge"), "b")
        return named.select(F.col("fa").alias("a"), F.col("fb").alias("b"))

    near = similar_of(stage, rows, texts, candidates(stage, keys, texts, None))
    links = links.unionByName(between(near))
    roots = connected_components(stage, links)
    placed = stage.keep(numbers.join(roots.select(F.col("node").alias("fp"), "root").hint("merge"), "fp").select("tid", "root"), "placed")
    lows = stage.keep(placed.groupBy("root").agg(F.min("tid").alias("low")), "lows")
    across = candidates(stage, keys, texts, placed.join(lows.hint("merge"), "root").select("tid", F.col("low").alias("root")))
    return links if across.isEmpty() else links.unionByName(between(similar_of(stage, rows, texts, across)))
