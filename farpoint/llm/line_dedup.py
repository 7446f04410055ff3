"""Repeated line runs from a suffix array over line-ID sequences; later copies go.

The suffixes of all texts' lines are put in order by prefix doubling (``suffix_order``), what neighbours in that order have in
common gives intervals of suffixes that begin with the same run of lines (``intervals``), and of each
interval all members but the one that stands first are later copies. For a suffix the deepest such interval tells the longest run from
there that an earlier place holds as well: the maximal run. Runs of ``min_chars`` characters or more go whole.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging
from farpoint.llm.intervals import longest_copies
from farpoint.llm.suffix_order import ordered_suffixes

MIN_CHARS = 50
ROW = "__row"


def window_lines(sizes: list[int], least: int) -> list[int]:
    """For each line the fewest lines from it on that hold ``least`` characters; 0 if all do not."""
    out, stop, held = [], 0, 0
    for start, size in enumerate(sizes):
        while held < least and stop < len(sizes):
            held += sizes[stop]
            stop += 1
        out.append(stop - start if held >= least else 0)
        held -= size
    return out


def _lines(least: int):
    names = ["row_no", "doc_id", "pos", "line_hash", "span"]
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int32()]

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows, strict=True)) or [[]] * len(names), kinds, strict=True)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for batch in batches:
            for row, doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                if not text.is_valid:
                    continue
                lines = text.as_py().split("\n")
                spans = window_lines([len(x) for x in lines], least)
                for i, (line, n) in enumerate(zip(lines, spans, strict=True)):
                    rows.append((row, doc, i, hashlib.md5(line.encode("utf-8", "surrogatepass")).digest(), n))
                    if len(rows) >= 20_000:
                        yield made(rows)
                        rows = []
        yield made(rows)

    return run


def later_copies(stage: Staging, rows: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """(__row, doc_id, text) -> (__row, pos, span) of the maximal runs that an earlier place holds too."""
    lines = stage.keep(rows.mapInArrow(_lines(min_chars), "row_no long, doc_id long, pos int, line_hash binary, span int"), "lines")
    suffixes, common = ordered_suffixes(stage, lines)
    enough = stage.keep(suffixes.where("span > 0 AND span <= rest"), "suffixes")
    place = F.struct("doc_id", "row_no", "pos")
    classes = enough.groupBy("rank").agg(F.min(place).alias("first"), F.first("span").alias("span"), F.count("*").alias("n"))
    classes = stage.keep(classes.join(common.hint("merge"), "rank", "left").select("rank", "first", "span", "n", F.coalesce("common", F.lit(0)).alias("common")), "classes")
    copied = longest_copies(stage, classes.select("rank", "first.doc_id", "first.row_no", "first.pos", "common", "span"))
    known = classes.select("rank", "first", "n").join(copied.hint("merge"), "rank").where("n > 1 OR copied > 0").select("rank", "first", "copied")
    known = stage.keep(known, "known")  # written, so that both sides of the join are plain exchanges and a hot class can be split
    length = F.when(place == F.col("first"), F.col("copied")).otherwise(F.col("rest"))
    return enough.join(known.hint("merge"), "rank").select(F.col("row_no").alias(ROW), "pos", length.alias("span")).where("span > 0")


def _cut(names: list[str], text_at: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans, texts, counts, gone = batch.column(batch.num_columns - 1), [], [], []
            for text, span in zip(batch.column(text_at), spans, strict=True):
                lines = text.as_py().split("\n") if text.is_valid else []
                counts.append(len(lines))
                if not span.is_valid:
                    texts.append(text.as_py())
                    gone.append(0)
                    continue
                pos, n = (c.to_numpy() for c in span.values.flatten())
                edge = np.zeros(len(lines) + 1, np.int32)
                np.add.at(edge, pos, 1)
                np.add.at(edge, pos + n, -1)
                stay = np.flatnonzero(np.cumsum(edge)[:-1] == 0)
                gone.append(len(lines) - len(stay))
                texts.append("\n".join(lines[i] for i in stay.tolist()))
            columns = [pa.array(texts, pa.string()) if i == text_at else batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(counts, pa.int64()), pa.array(gone, pa.int64())], names=[*names, "n_lines", "n_removed"])

    return run


def line_dedup(spark: SparkSession, docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """``docs`` with later copies deleted from ``text``, and the columns n_lines and n_removed.

    Every line of a run of ``min_chars`` characters or more goes that an earlier place holds as well, line by line.
    Lines end at a newline. Earlier means a smaller doc_id (null first), then the row, then the place, so copies may overlap.
    Null text stays null with no lines, the empty text is one empty line, an empty table gives
    none; a row repeated with the same id and text keeps one copy; other columns stay (those named
    n_lines, n_removed or __row are replaced).
    """
    stage = Staging(spark, "lines")
    docs = docs.drop("n_lines", "n_removed", ROW)
    rows = stage.keep(docs.withColumn(ROW, F.monotonically_increasing_id()), "rows")
    with stage.scratch() as tmp:
        copies = later_copies(tmp, rows.select(ROW, F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), min_chars)
        spans = stage.keep(copies.groupBy(ROW).agg(F.collect_list(F.struct("pos", "span")).alias("__spans")), "spans")
    joined = rows.join(spans.hint("shuffle_hash"), ROW, "left")  # spans grow with the lines: not to be broadcast
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return joined.select(*[F.col(f"`{c}`") for c in docs.columns], "__spans").mapInArrow(_cut(docs.columns, docs.columns.index("text")), schema + ", n_lines long, n_removed long")
