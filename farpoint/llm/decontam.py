"""Benchmark decontamination as a prefix-filtered set join, with DataFrame functions only.

The records of the join are the item-sized windows of the benchmark (13 consecutive words, or the
whole item where it is shorter), their tokens are shingles of SHINGLE words (the whole window where
it is shorter) in the order of rarity, by counts over all documents. Containment has to be complete, so by
the prefix principle one token of a window is enough to find every document position that can
hold it: its rarest shingle. Each occurrence of that shingle fixes the only possible start of the
window (positional bound), the window has to end inside the document (length bound), and what
is left is verified word by word, all in the stage that scans the text. Only verified windows
are shuffled.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging, ascii_lower, repeat_rows, text_hash, without_rows

NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WINDOW = 13
#: Words of a token of the join.
SHINGLE = 3
#: Windows broadcast at once (about 200 bytes each); a larger benchmark is taken in blocks.
BLOCK_WINDOWS = 100_000


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), NOT_WORD), "")


def benchmark_windows(benchmark: DataFrame, window: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """Distinct windows with the sorted ids (as text) of the items that hold them; an item without an id has windows and no id to list."""
    items = benchmark.select(F.col(id_col).cast("string").alias("item_id"), words_of(F.col(text_col)).alias("item_words"))
    items = items.withColumn("n", F.size("item_words")).where("n > 0")
    starts = F.explode_outer(F.sequence(F.lit(1), F.greatest(F.col("n") - window + 1, F.lit(1))))
    return (
        items.select("item_id", "item_words", starts.alias("at"))
        .select("item_id", F.expr(f"slice(item_words, at, {window})").alias("win"))
        .groupBy("win").agg(F.sort_array(F.collect_set("item_id")).alias("items"))
    )


def shingles_of(words: str, size: int) -> Column:
    """The shingles of an array of words, in order: xxhash64 of each, seeded with the size by its first argument."""
    shifted = [F.col(words) if i == 0 else F.slice(words, i + 1, F.greatest(F.size(words) - i, F.lit(0))) for i in range(size)]
    return F.arrays_zip(*[x.alias(f"s{i}") for i, x in enumerate(shifted)])


def with_tokens(rows: DataFrame, words: str, size: int, *keep: str) -> DataFrame:
    """A row for each shingle in ``words``: its place ``pos`` and its ``token``. Equal tokens are only candidates, the words decide."""
    each = rows.select(*keep, F.posexplode(shingles_of(words, size)).alias("pos", "shingle")).where(F.col(f"shingle.s{size - 1}").isNotNull())
    return each.select(*keep, "pos", F.xxhash64(F.lit(size), *[F.col(f"shingle.s{i}") for i in range(size)]).alias("token"))


def contamination(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20, block_windows: int = BLOCK_WINDOWS, stage: Staging | None = None) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    A word inside any occurrence of a window is hit; contaminated means n_hit > 0 and
    share * n_hit >= n_words. Null text has no words; repeated rows each get a row; items without
    words have no windows, items without id count in n_hit and not among the items; further columns are
    ignored; either table may be empty.
    """
    stage = stage or Staging(spark, "decontam")
    words = words_of(F.col("text"))
    base = stage.keep(
        docs.select("doc_id", F.array_join(words, " ").alias("body")).select("doc_id", "body", F.xxhash64("body").alias("body_hash"), F.when(F.col("body") == "", 0).otherwise(F.length("body") - F.length(F.replace(F.col("body"), F.lit(" "))) + 1).cast("long").alias("n_words")),
        "words",
    )
    wins = stage.keep(benchmark_windows(benchmark, window), "windows")
    wins = wins.withColumn("win_len", F.size("win"))
    sizes = [r.n for r in wins.select(F.least("win_len", F.lit(SHINGLE)).alias("n")).distinct().orderBy("n").collect()]  # 1 to SHINGLE
    few = wins.count() <= block_windows  # then their shingles are few as well
    found = None
    for size in sizes:
        own = with_tokens(wins.where(F.least("win_len", F.lit(SHINGLE)) == size), "win", size, "win", "items", "win_len")
        tokens = own.select("token").distinct()
        scan = base.where("n_words > 0").select(F.split("body", " ").alias("doc_words"))
        counts = with_tokens(scan, "doc_words", size).join(F.broadcast(tokens) if few else tokens, "token").groupBy("token").agg(F.count("*").alias("df"))
        spread = own.join(F.broadcast(counts) if few else counts, "token")
        every = F.col("win_len") - size + 1  # a shingle that no document has rules its window out
        rarest = stage.keep(
            spread.groupBy("win").agg(F.min(F.struct("df", "token", "pos")).alias("prefix"), F.count("*").alias("n"), F.first("items").alias("items"), F.first("win_len").alias("win_len"))
            .where(F.col("n") == every)
            .select(F.col("prefix.token").alias("token"), F.col("prefix.pos").alias("offset"), "win", "win_len", "items"),
            f"prefixes-{size}",
        )
        blocks = max(1, math.ceil(rarest.count() / block_windows))
        for block in range(blocks):
            part = rarest if blocks == 1 else rarest.where(F.pmod(F.xxhash64("token", "win"), F.lit(blocks)) == block)
            hits = find_windows(base, part, size)
            found = hits if found is None else found.unionByName(hits)
    every = base.select("doc_id", "body_hash", "n_words", F.lit(1).cast("long").alias("copies"), F.lit(None).cast("struct<start:int,win_len:int>").alias("span"), F.lit(None).cast("array<string>").alias("items"))
    per_doc = (
        (every if found is None else every.unionByName(found.withColumn("copies", F.lit(0).cast("long"))))
        .groupBy("doc_id", "body_hash", "n_words")
        .agg(F.sum("copies").alias("copies"), F.collect_set("span").alias("spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("items"))
    )
    covered = F.expr(
        "aggregate(array_sort(spans), named_struct('n', 0L, 'e', 0), (s, x) -> named_struct("
        "'n', s.n + greatest(x.start + x.win_len - greatest(s.e, x.start), 0), 'e', greatest(s.e, x.start + x.win_len)), s -> s.n)"
    )
    out = repeat_rows(per_doc.select("doc_id", "n_words", "copies", covered.alias("n_hit"), F.sort_array("items").alias("items")), "copies")
    return out.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (F.col("n_hit") * share >= F.col("n_words"))).alias("contaminated"),
    )


def find_windows(base: DataFrame, prefixes: DataFrame, size: int) -> DataFrame:
    """Verified occurrences by tokens of one size: prefix-token probe, positional and length bounds, then the words.

    The words of a document stay with its scan's stage up to the verdict; no row of it is written with them.
    """
    scan = base.where("n_words > 0").select("doc_id", "body_hash", "n_words", F.split("body", " ").alias("doc_words"))
    at = with_tokens(scan, "doc_words", size, "doc_id", "body_hash", "n_words", "doc_words")
    start = F.col("pos") - F.col("offset")
    cand = at.join(F.broadcast(prefixes), "token").where((start >= 0) & (start + F.col("win_len") <= F.col("n_words")))
    same = F.slice("doc_words", start + 1, F.col("win_len")) == F.col("win")
    return cand.where(same).select("doc_id", "body_hash", "n_words", F.struct(start.alias("start"), "win_len").alias("span"), "items")


def drop_contaminated(spark: SparkSession, docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Documents that the rule clears, all columns. Rows are judged one by one, whatever their ids."""
    keyed = docs.select(F.struct("doc_id", text_hash().alias("text_hash")).alias("doc_id"), "text")
    stage = Staging(spark, "clean")
    with stage.scratch() as tmp:
        bad = contamination(spark, keyed, benchmark, stage=tmp).where("contaminated").select("doc_id.doc_id", "doc_id.text_hash")
        return without_rows(stage, docs, bad)
