"""Token shards in training order.

Each document becomes sequences of a fixed number of tokens. A keyed Feistel network with
cycle-walking permutes their numbers into global slots, and the shard of a slot range is written by one
task, in slot order and with a fixed stride: slot s is at byte (s - first slot) * stride of its shard,
so a reader starts anywhere. The slots are taken in rounds of shard ranges, so what lies in
shuffle files at a time is a part of the tokens only.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import sys
import uuid
from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

TOKENIZER = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: The pre-tokenisation pattern that belongs to the vocabulary file (fixed value).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
END_OF_TEXT = 50256
PAD = 0xFFFF
LENGTH = 512
SHARD_SEQUENCES = 16_384
ROUNDS = 4
KEY = 0x5EED


@functools.cache
def encoding(path: str):
    import tiktoken

    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("shards", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def feistel(index: np.ndarray, size: int, key: int, rounds: int = 6) -> np.ndarray:
    """A permutation of range(size), at the numbers ``index``; walks on while outside the range."""
    half = max(1, (max(size - 1, 1).bit_length() + 1) // 2)
    mask = np.uint64((1 << half) - 1)
    keys = [np.uint64(int.from_bytes(hashlib.blake2b(f"{key}:{r}".encode(), digest_size=8).digest(), "little")) for r in range(rounds)]
    out = index.astype(np.uint64)
    walk = np.ones(len(out), bool)
    with np.errstate(over="ignore"):
        while walk.any():
            left, right = out[walk] >> np.uint64(half), out[walk] & mask
            for k in keys:
                mixed = (right ^ k) * np.uint64(0x9E3779B97F4A7C15)
                mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
                left, right = right, left ^ ((mixed ^ (mixed >> np.uint64(32))) & mask)
            out[walk] = (left << np.uint64(half)) | right
            walk = out >= size
    return out.astype(np.int64)


def _sequences(path: str, length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, press = encoding(path).encode_ordinary, zstandard.ZstdCompressor(level=3).compress
        part, number = TaskContext.get().partitionId(), 0
        kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()]
        names = ["part", "number", "doc_id", "chunk", "n_tokens", "tokens"]
        rows: list[tuple] = []
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = array("H", encode(text.as_py() or ""))
                ids.append(END_OF_TEXT)
                if sys.byteorder == "big":
                    ids.byteswap()
                data = ids.tobytes()
                for chunk, at in enumerate(range(0, len(data), 2 * length)):
                    piece = data[at : at + 2 * length]
                    rows.append((part, number, doc, chunk, len(piece) // 2, press(piece)))
                    number += 1
                if len(rows) >= 2000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)
                    rows = []
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return run


def _shards(folder: str, length: int):
    """Rows sorted by slot, one shard after another -> files; gives the place of each sequence."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = pafs.FileSystem.from_uri(folder)
        inflate = zstandard.ZstdDecompressor().decompress
        shard, out, path = None, None, ""
        for batch in batches:
            paths = []
            for no, n, tokens in zip(*(batch.column(i).to_pylist() for i in (0, 4, 5)), strict=True):
                if no != shard:
                    if out:
                        out.close()
                    store.create_dir(root, recursive=True)
                    shard, path = no, f"{root}/shard-{no:08d}-{uuid.uuid4().hex}.bin"  # an attempt's own name
                    out = store.open_output_stream(path)
                out.write(inflate(tokens) + b"\xff\xff" * (length - n))
                paths.append(path)
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(5)), pa.array(paths, pa.string())], names=["shard", "slot", "doc_id", "chunk", "n_tokens", "path"])
        if out:
            out.close()

    return run


def write_shards(
    spark: SparkSession, docs: DataFrame, stage: Staging, tokenizer: str = TOKENIZER, length: int = LENGTH, shard_sequences: int = SHARD_SEQUENCES, rounds: int = ROUNDS, key: int = KEY
) -> DataFrame:
    """Writes the shards; returns (shard, slot, doc_id, chunk, n_tokens, path), the index of the sequences.

    A document's tokens end with END_OF_TEXT and are cut every ``length`` tokens, the last sequence
    is padded with PAD; null counts as empty, so each row has a sequence. Sequences are numbered
    in the order in which the table is read.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    made = stage.keep(rows.mapInArrow(_sequences(tokenizer, length), "part int, number long, doc_id long, chunk int, n_tokens int, tokens binary"), "sequences")
    sizes = sorted((r.part, r.n) for r in made.groupBy("part").agg(F.count("*").alias("n")).collect())  # a row for each task of the scan
    size, firsts = 0, []
    for part, n in sizes:
        firsts.append((part, size))
        size += n
    if not size:
        return spark.createDataFrame([], "shard int, slot long, doc_id long, chunk int, n_tokens int, path string")
    first = F.broadcast(spark.createDataFrame(firsts, "part int, first long"))
    slot_of = F.pandas_udf(lambda index: pd.Series(feistel(index.to_numpy(), size, key)), "long")
    placed = made.join(first, "part").withColumn("slot", slot_of(F.col("first") + F.col("number")))
    placed = placed.withColumn("shard", F.floor(F.col("slot") / shard_sequences).cast("int"))
    n_shards = -(-size // shard_sequences)
    per_round, folder, index = -(-n_shards // rounds), stage.path("shards"), None
    for low in range(0, n_shards, per_round):
        high = min(low + per_round, n_shards)
        part = placed.where((F.col("shard") >= low) & (F.col("shard") < high)).select("shard", "slot", "doc_id", "chunk", "n_tokens", "tokens")
        ranged = part.repartitionById(high - low, F.col("shard") - low).sortWithinPartitions("slot")
        done = stage.keep(ranged.mapInArrow(_shards(folder, length), "shard int, slot long, doc_id long, chunk int, n_tokens int, path string"), "index")
        index = done if index is None else index.unionByName(done)
    stage.drop(made)
    return index


def _read(folder: str, length: int):
    stride = 2 * length

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = pafs.FileSystem.from_uri(folder)
        for batch in batches:
            for path, first, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                with store.open_input_file(path) as file:
                    at, end = (start - first) * stride, file.size()
                    while at < end:
                        data = file.read_at(min(stride * 1024, end - at), at)
                        rows = [data[i : i + stride].rstrip(b"\xff") for i in range(0, len(data), stride)]  # no id ends with the pad's byte
                        slots = pa.array(range(first + at // stride, first + at // stride + len(rows)), pa.int64())
                        yield pa.RecordBatch.from_arrays([slots, pa.array(rows, pa.binary())], names=["slot", "tokens"])
                        at += len(data)

    return run


def read_shards(index: DataFrame, stage: Staging, length: int = LENGTH, shard_sequences: int = SHARD_SEQUENCES, resume_at: int = 0) -> DataFrame:
    """(slot, tokens without padding) from ``resume_at`` on, read from the shard files alone."""
    files = index.select("path", (F.col("shard").cast("long") * shard_sequences).alias("first")).distinct().where(F.col("first") + shard_sequences > resume_at)
    todo = files.select("path", "first", F.greatest("first", F.lit(resume_at)).alias("start"))
    return todo.repartition("path").mapInArrow(_read(stage.root, length), "slot long, tokens binary")


def shard_round_trip(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Per sequence: doc_id, chunk, n_tokens, slot, shard, tokens_sha256 (of the little-endian ids).

    Writes all shards, then reads them back. Repeated rows, null ids and null texts have sequences like
    any other; an empty table has none; other columns are ignored.
    """
    stage = Staging(spark, "shards")
    index = write_shards(spark, docs, stage)
    back = read_shards(index, stage).select("slot", (F.octet_length("tokens") / 2).cast("int").alias("n_tokens"), F.sha2("tokens", 256).alias("tokens_sha256"))
    # by merging: both sides have a row for each sequence
    return index.select("slot", "shard", "doc_id", "chunk").hint("merge").join(back, "slot").select("doc_id", "chunk", "n_tokens", "slot", "shard", "tokens_sha256")
