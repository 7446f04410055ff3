"""WARC archives: writing with revisit records, and a parallel reader that verifies boundaries.

An archive has no index, and a payload may itself hold the text that a record begins with. The
reader cuts files into byte blocks. In each block a task takes every place that could be a record
and where that record would end, and follows these offsets to the first one outside the block.
Pointer jumping over the blocks from offset 0 of each file then leaves the one true entry of each
block, from which a second pass reads the records.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

MAGIC = b"WARC/1.1\r\n"
LEAST_REVISIT = 1000
ARCHIVE_BYTES = 64 << 20
BLOCK_BYTES = 8 << 20
HEADER_BYTES = 1 << 16
LENGTH = b"\r\nContent-Length: "
BROADCAST_ROWS = 500_000
RECORD = "path string, at long, record_type string, page_id long, uri string, payload_bytes long, payload_digest string, refers_to long"


def record_bytes(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, revisit: bool, date: str) -> bytes:
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    head = [
        f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {date}",
        f"WARC-Target-URI: {quote(url or '', safe=':/?#[]@!$&()*+,;=%~')}", f"WARC-Payload-Digest: sha1:{base64.b32encode(hashlib.sha1(payload).digest()).decode()}",
        "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}",
    ]
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return MAGIC + "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def _writer(folder: str, limit: int, date: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = pafs.FileSystem.from_uri(folder)
        done, out, size, path = [], None, 0, ""
        for batch in batches:
            for page_id, url, html, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if out is None:
                    store.create_dir(root, recursive=True)
                    path, size = f"{root}/{uuid.uuid4().hex}.warc", 0  # an attempt's own name; only what ends is told on
                    out = store.open_output_stream(path)
                data = record_bytes(page_id, url, (html or "").encode("utf-8", "surrogatepass"), refers, refers is not None, date)
                out.write(data)
                size += len(data)
                if size >= limit:
                    out.close()
                    done.append((path, size))
                    out = None
        if out is not None:
            out.close()
            done.append((path, size))
        yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in done], pa.string()), pa.array([s for _, s in done], pa.int64())], names=["path", "bytes"])

    return run


def revisits(pages: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """(page_id, payload_hash, refers_to) of the pages whose payload another page records."""
    narrow = pages.select("page_id", F.unhex(F.sha2("html", 256)).alias("payload_hash"), F.octet_length("html").alias("size")).where(F.col("size") >= least)
    groups = narrow.groupBy("payload_hash").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1")
    return narrow.join(groups, "payload_hash").where(~F.col("page_id").eqNullSafe(F.col("refers_to"))).select("page_id", "payload_hash", "refers_to").distinct()


def write_warc(spark: SparkSession, pages: DataFrame, stage: Staging, least: int = LEAST_REVISIT, archive_bytes: int = ARCHIVE_BYTES, date: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Writes the archives; returns (path, bytes) of the files that ended well."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    marks = stage.keep(revisits(pages, least), "revisits")
    if marks.count() <= BROADCAST_ROWS:
        marks = F.broadcast(marks)
    marks = marks.select(F.col("page_id").alias("r_id"), F.col("payload_hash").alias("r_hash"), "refers_to")
    full = pages.withColumn("payload_hash", F.unhex(F.sha2("html", 256)))
    joined = full.join(marks, full["page_id"].eqNullSafe(marks["r_id"]) & (full["payload_hash"] == marks["r_hash"]), "left")
    written = joined.select("page_id", "url", "html", "refers_to").mapInArrow(_writer(stage.path("archives"), archive_bytes, date), "path string, bytes long")
    return stage.keep(written, "manifest")


class _Window:
    """Reads of a file that mostly fall into one range."""

    def __init__(self, store, path: str, start: int, size: int):
        self.file, self.start = store.open_input_file(path), start
        self.end = self.file.size()
        self.data = self.file.read_at(min(size, self.end - start), start)
        self.blank_from = self.blank = self.end  # no blank line begins in between; one does at blank, unless that is the end
        self.length_of, self.length_from, self.length = -1, 0, -1  # of the header that ends at length_of: its last length line

    def read(self, at: int, size: int) -> bytes:
        size = max(0, min(size, self.end - at))
        lo = at - self.start
        if lo >= 0 and lo + size <= len(self.data):
            return self.data[lo : lo + size]
        return self.file.read_at(size, at)

    def find(self, what: bytes, at: int, stop: int) -> int:
        """The first place in [at, stop) where ``what`` begins, or -1."""
        if at >= self.start and (lo := self.data.find(what, at - self.start, stop - self.start + len(what) - 1)) >= 0:
            return self.start + lo
        if at >= self.start:
            at = max(at, self.start + len(self.data) - len(what) + 1)
        size = 1 << 16
        while at < stop:
            part = self.read(at, size + len(what) - 1)
            if (lo := part.find(what)) >= 0:
                return at + lo if at + lo < stop else -1
            at, size = at + size, min(2 * size, 1 << 22)
        return -1

    def header_stop(self, at: int) -> int:
        """The first blank line from ``at`` on, or the file's end. Places asked for backwards are searched once in all."""
        if not self.blank_from <= at <= self.blank:
            back = at < self.blank_from
            found = self.find(b"\r\n\r\n", at, self.blank_from if back else self.end)
            self.blank = found if found >= 0 else self.blank if back else self.end
            self.blank_from = at
        return self.blank

    def length_line(self, at: int, stop: int) -> int:
        """The last length line in [at, stop), or -1."""
        if self.length_of != stop:
            self.length_of, self.length_from, self.length = stop, stop, -1
        if at < self.length_from:
            if self.length < 0:
                found = self.read(at, min(self.length_from + len(LENGTH) - 1, stop) - at).rfind(LENGTH)
                self.length = at + found if found >= 0 else -1
            self.length_from = at
        return self.length if self.length >= at else -1


def record_ends(window: _Window, at: int) -> tuple[int, int, int] | None:
    """End of the header, start of the block and start of the next record; None where no record can stand. Headers may have any length."""
    if window.read(at, len(MAGIC)) != MAGIC or (stop := window.header_stop(at)) == window.end or (line := window.length_line(at, stop)) < 0:
        return None
    size = window.read(line + len(LENGTH), min(64, stop - line - len(LENGTH))).split(b"\r\n")[0]
    if not re.fullmatch(rb"\d{1,18}", size):
        return None
    block = stop + 4
    after = block + int(size) + 4
    return (stop, block, after) if after <= window.end else None


def parse_header(window: _Window, at: int) -> tuple[dict[str, str], int, int] | None:
    """Fields, start of the block and start of the next record; None where no record can stand."""
    if (found := record_ends(window, at)) is None:
        return None
    stop, block, after = found
    head = window.read(at + len(MAGIC), stop - at - len(MAGIC)).decode("latin-1")
    return dict(x.split(": ", 1) for x in head.split("\r\n") if ": " in x), block, after


def _candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each block: every possible record, and where its chain leaves the block."""
    for batch in batches:
        for folder, path, start, stop in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            store, _ = pafs.FileSystem.from_uri(folder)
            window = _Window(store, path, start, stop - start + HEADER_BYTES)
            places, at = [], window.data.find(MAGIC)
            while 0 <= at < stop - start:
                places.append(start + at)
                at = window.data.find(MAGIC, at + 1)
            leaves: dict[int, int] = {}
            for place in reversed(places):
                if found := record_ends(window, place):
                    after = found[2]
                    out = after if after >= stop else leaves.get(after)
                    if out is not None:
                        leaves[place] = out
            window.file.close()
            n = len(leaves)
            yield pa.RecordBatch.from_arrays([pa.array([path] * n, pa.string()), pa.array(list(leaves), pa.int64()), pa.array(list(leaves.values()), pa.int64())], names=["path", "at", "after"])


def _records(with_payload: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for folder, path, at, stop in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                store, _ = pafs.FileSystem.from_uri(folder)
                window, rows, held = _Window(store, path, at, stop - at + HEADER_BYTES), [], 0
                while at < stop and (found := parse_header(window, at)):
                    fields, block, after = found
                    http = window.read(block, min(HEADER_BYTES, after - 4 - block))
                    body = block + http.find(b"\r\n\r\n") + 4
                    if fields["WARC-Type"] == "revisit":
                        size = int(re.search(rb"Content-Length: (\d+)", http)[1])
                        digest = base64.b32decode(fields["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
                        payload = None
                    else:
                        size, sha = after - 4 - body, hashlib.sha1()
                        for x in range(body, after - 4, 1 << 20):
                            sha.update(window.read(x, min(1 << 20, after - 4 - x)))
                        digest, payload = sha.hexdigest(), window.read(body, size) if with_payload else None
                    ids = [int(m[1]) if (m := re.fullmatch(r"<urn:page:(-?\d+)>", fields.get(k, ""))) else None for k in ("WARC-Record-ID", "WARC-Refers-To")]
                    rows.append((path, at, fields["WARC-Type"], ids[0], fields.get("WARC-Target-URI"), size, digest, ids[1], payload))
                    held += len(payload or b"")
                    if len(rows) >= 10_000 or held > 8 << 20:
                        yield _batch(rows, with_payload)
                        rows, held = [], 0
                    at = after
                window.file.close()
                yield _batch(rows, with_payload)

    return run


def _batch(rows: list[tuple], with_payload: bool) -> pa.RecordBatch:
    kinds = [("path", pa.string()), ("at", pa.int64()), ("record_type", pa.string()), ("page_id", pa.int64()), ("uri", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())]
    kinds = kinds if with_payload else kinds[:-1]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, (_, k) in enumerate(kinds)], names=[n for n, _ in kinds])


def _entries(stage: Staging, manifest: DataFrame, blocks: DataFrame, n_blocks: int) -> DataFrame:
    """(path, at) of the first true record of each block, by pointer jumping from each file's start."""
    leaps = stage.keep(blocks.mapInArrow(_candidates, "path string, at long, after long"), "leaps")
    entries = stage.keep(leaps.where("at = 0").select("path", "at"), "entries")
    known, jumps = entries.count(), leaps
    every = leaps.select("path", "at").hint("merge")  # a row for each possible record: not to be broadcast
    while n_blocks > 1:
        ahead = jumps.join(entries, ["path", "at"], "left_semi").select("path", F.col("after").alias("at")).join(every, ["path", "at"], "left_semi")
        entries = stage.keep(entries.unionByName(ahead).distinct(), "entries")
        if (now := entries.count()) == known:
            break
        known = now
        far = jumps.select("path", F.col("at").alias("after"), F.col("after").alias("far")).hint("merge")
        jumps = stage.keep(jumps.join(far, ["path", "after"], "left").select("path", "at", F.coalesce("far", "after").alias("after")), "jumps")
    ends = leaps.join(entries.hint("merge"), ["path", "at"], "left_semi").groupBy("path").agg(F.max("after").alias("after"))
    broken = manifest.where("bytes > 0").join(ends, "path", "left").where("after IS NULL OR after <> bytes").select("path", "bytes").head()
    if broken is not None:
        raise ValueError(f"the records of {broken.path} do not end at its {broken.bytes} bytes")
    return entries


def read_warc(spark: SparkSession, manifest: DataFrame, stage: Staging, block_bytes: int = BLOCK_BYTES, with_payload: bool = False) -> DataFrame:
    """One row per true record of the files (path, bytes); an error where the records do not fill a file."""
    root = F.lit(stage.root)
    blocks = manifest.where("bytes > 0").select("path", "bytes", F.explode(F.expr(f"sequence(0L, bytes - 1, {block_bytes}L)")).alias("start"))
    blocks = stage.keep(blocks.select("path", "bytes", "start", F.least(F.col("start") + block_bytes, "bytes").alias("stop")), "blocks")
    n_blocks = max(1, blocks.count())
    spread = blocks.repartition(min(n_blocks, 10_000), "path", "start")
    with stage.scratch() as tmp:
        entries = stage.keep(_entries(tmp, manifest, spread.select(root, "path", "start", "stop"), n_blocks), "entries")
    place = F.expr(f"at - at % {block_bytes}")
    starts = entries.withColumn("start", place).join(blocks, ["path", "start"])
    todo = starts.select(root.alias("root"), "path", "at", "stop").repartition(min(n_blocks, 10_000), "path", "at")
    return todo.mapInArrow(_records(with_payload), RECORD + (", payload binary" if with_payload else ""))


def warc_round_trip(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """Per page: page_id, payload_bytes, payload_digest, record_type, refers_to, read back from archives.

    Null html is an empty payload. Of equal payloads of LEAST_REVISIT bytes or more the largest
    page_id is the response (rows repeated with that very id are responses too), the others revisit
    it. Null url is an empty URI, a null page_id stays null and revisits like any other; an
    empty table writes no archive; other columns are ignored.
    """
    stage = Staging(spark, "warc")
    records = read_warc(spark, write_warc(spark, pages, stage), stage)
    return records.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
