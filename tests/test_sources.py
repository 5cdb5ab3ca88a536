"""Readers and writers."""

import gzip


def _record(kind, url, body):
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n\r\n" + body if kind == "response" else body
    return f"WARC/1.0\r\nWARC-Type: {kind}\r\nWARC-Target-URI: {url}\r\nWARC-Date: 2024-04-01T00:00:00Z\r\nContent-Length: {len(http)}\r\n\r\n".encode() + http + b"\r\n\r\n"


def test_web_archives(spark, tmp_path):
    from mlcurate.sources import warc

    one = _record("warcinfo", "", b"software: x") + _record("response", "http://a.com/1", "<p>né WARC/1.0</p>".encode()) + _record("request", "http://a.com/1", b"GET") + _record("response", "http://a.com/2", b"")
    (tmp_path / "x.warc").write_bytes(one)
    (tmp_path / "y.warc.gz").write_bytes(gzip.compress(_record("response", "http://b.com/", b"<p>b</p>")))
    (tmp_path / "z.warc").write_bytes(b"WARC/1.0\r\nbroken")
    got = sorted((r.url, r.html) for r in warc.read(spark, str(tmp_path)).collect())
    assert got == [("http://a.com/1", "<p>né WARC/1.0</p>"), ("http://a.com/2", ""), ("http://b.com/", "<p>b</p>")]


def test_files(spark, tmp_path):
    from mlcurate import io

    df = spark.createDataFrame([(1, "en", "a"), (2, "de", "b")], "doc_id long, lang string, text string")
    io.write_by_label(df, str(tmp_path / "p"))
    assert spark.read.parquet(str(tmp_path / "p")).where("lang = 'de'").count() == 1
    io.write_jsonl(df, str(tmp_path / "j"))
    assert io.read_jsonl(spark, str(tmp_path / "j"), "doc_id long, lang string, text string").count() == 2
    df.write.orc(str(tmp_path / "o"))
    assert io.read_orc(spark, str(tmp_path / "o")).count() == 2
    df.write.option("header", True).csv(str(tmp_path / "c"))
    assert io.read_csv(spark, str(tmp_path / "c"), "doc_id long, lang string, text string").agg({"doc_id": "sum"}).first()[0] == 3
    df.select("text").write.text(str(tmp_path / "t"))
    assert io.read_lines(spark, str(tmp_path / "t")).count() == 2
