"""Web-archive files: response records as (page_id, url, html, date), read through Spark's own file access."""

from __future__ import annotations

import gzip
import zlib

from pyspark.sql import DataFrame, SparkSession

from mlcurate.session import prepare

SCHEMA = "page_id long, url string, html string, date string"


def records(data: bytes):
    """(url, date, body) of the response records of one file, gzipped or not; stops at the first damaged record."""
    if data[:2] == b"\x1f\x8b":
        try:
            data = gzip.decompress(data)
        except (EOFError, OSError, zlib.error):
            return
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        head = {}
        for line in data[at:end].split(b"\r\n")[1:]:
            k, _, v = line.partition(b":")
            head[k.strip().lower()] = v.strip().decode("utf-8", "replace")
        try:
            n = int(head.get(b"content-length", ""))
        except ValueError:
            return
        body = data[end + 4 : end + 4 + n]
        if head.get(b"warc-type") == "response":
            # what stands before the first empty line is the protocol's header
            yield head.get(b"warc-target-uri", ""), head.get(b"warc-date", ""), body.partition(b"\r\n\r\n")[2]
        at = end + 4 + n


def read(spark: SparkSession, path: str) -> DataFrame:
    """All response records below ``path``; page_id is a hash of URL and date. One task reads a file at a time."""
    prepare(spark)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for data in b.column(0):
                rows = [(zlib.crc32(f"{u} {d}".encode()), u, t.decode("utf-8", "replace"), d) for u, d, t in records(data.as_py() or b"")]
                if rows:
                    kinds = (pa.int64(), pa.string(), pa.string(), pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["page_id", "url", "html", "date"])

    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content").mapInArrow(run, SCHEMA)
