import hashlib

import pytest

from farpoint.llm import warc
from farpoint.llm.common import Staging


def test_headers_of_any_length(spark):
    rows = [(1, "http://a/", "first"), (2, "http://b/" + "é" * 60_000, "WARC/1.1\r\n" * 30_000), (3, "u" * 300_000, "after"), (4, "c", "WARC/1.1\r\nContent-Length: 3\r\n" * 20), (5, None, "last")]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    want = sorted((p, len(h), hashlib.sha1(h.encode()).hexdigest()) for p, _, h in rows)
    for block in (8 << 20, 10_000):
        stage = Staging(spark, "test")
        files = warc.write_warc(spark, frame, stage)
        got = warc.read_warc(spark, files, stage, block_bytes=block).collect()
        assert sorted((r.page_id, r.payload_bytes, r.payload_digest) for r in got) == want


def test_records_that_do_not_fill_a_file_are_an_error(spark):
    stage = Staging(spark, "test")
    files = warc.write_warc(spark, spark.createDataFrame([(1, "a", "x" * 50), (2, "b", "y" * 50)], "page_id long, url string, html string").coalesce(1), stage)
    path = files.collect()[0].path
    with open(path, "rb") as f:
        data = f.read()
    with open(path, "wb") as f:
        f.write(data.replace(b"WARC/1.1", b"WARC/9.9").replace(b"WARC/9.9", b"WARC/1.1", 1))  # the second record does not begin
    with pytest.raises(ValueError):
        warc.read_warc(spark, files, stage).collect()
