"""Exact deduplication by a 128-bit content hash, with bytes compared inside each hash group.

Only DataFrame functions. The copies of a text are collapsed on the map side (the grouping key
holds the hash *and* the text, so equal hashes of different bytes stay apart), and what is joined
back to the documents is one narrow row per text.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.llm.common import SPACE_RUN, repeat_rows


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_RUN, " ")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest: Callable[[Column], Column] = F.md5) -> DataFrame:
    """One row per input row: its id, keep_id, group_size, kept, text_sha256.

    Equal texts are those identical after every white-space run became one space. The smallest id
    stays (nulls last: a null id stays only in a group that has no other). A row repeated with the
    same id and text stays once. Null text counts as empty, an empty table gives an empty result,
    further columns of ``docs`` are ignored whatever they are called. ``digest`` is replaceable
    so that tests can force collisions.
    """
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), normalised(F.col(f"`{text_col}`")).alias("body"))
    hashed = rows.select("doc_id", "body", F.unhex(digest(F.col("body"))).alias("content_hash"))
    groups = (
        hashed.groupBy("content_hash", "body")
        .agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
        .select("content_hash", F.sha2("body", 256).alias("text_sha256"), "keep_id", "group_size")
    )
    # the second digest tells apart texts of one colliding content hash that the grouping has found to differ
    members = hashed.groupBy("doc_id", "content_hash", F.sha2("body", 256).alias("text_sha256")).agg(F.count("*").alias("copies"))
    joined = members.join(groups, ["content_hash", "text_sha256"])
    out = repeat_rows(joined, "copies")
    kept = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("copy_no") == 1)
    return out.select("doc_id", "keep_id", "group_size", kept.alias("kept"), "text_sha256")


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, all columns. Rows are told apart by id and text, so ids may be null or repeated; of rows equal in both one stays."""
    marks = exact_dedup(docs, id_col, text_col)
    marks = marks.where(F.col("doc_id").eqNullSafe(F.col("keep_id"))).groupBy("doc_id", "text_sha256").agg(F.count("*").alias("copies"))
    marks = marks.select(F.col("doc_id").alias("__kept_id"), F.col("text_sha256").alias("__kept_hash"), "copies")
    own = F.sha2(normalised(F.col(f"`{text_col}`")), 256)
    left = docs.withColumn("__hash", own)
    left = left.join(marks.select("__kept_id", "__kept_hash"), left[id_col].eqNullSafe(F.col("__kept_id")) & (F.col("__hash") == F.col("__kept_hash")), "left_semi")
    if not marks.where("copies > 1").isEmpty():
        left = left.dropDuplicates([id_col, "__hash"])
    return left.drop("__hash")
