import gzip
import hashlib
import io

import pytest
from pyspark.sql import functions as F

from freeseg.llm import warc

PAGES = "page_id long, url string, html string, digest string, path string"


def pages(spark, texts):
    return spark.createDataFrame([(k, f"http://x.y/{k} ü", t, "d", "p") for k, t in enumerate(texts)], PAGES)


def test_payloads_come_back(spark):
    big = "<p>é" + "x" * 200_000
    texts = [big, "small", None, big, "small", "y" * 100, "y" * 100, "", "line\r\n\r\nline", "\x00" * 300]
    rows = sorted(warc.round_trip(pages(spark, texts).repartition(3)).collect(), key=lambda r: r.page_id)
    firsts = {}
    for k, (t, r) in enumerate(zip(texts, rows, strict=True)):
        raw = (t or "").encode()
        assert r.payload_bytes == len(raw) and r.payload_digest == hashlib.sha256(raw).hexdigest() and r.verified
        first = firsts.setdefault(raw, k) if len(raw) >= 100 else k
        if first == k:
            assert r.record_type == "response" and r.refers_to is None and bytes(r.payload) == raw
        else:
            assert r.record_type == "revisit" and r.refers_to == first and r.payload is None


def test_each_record_is_a_gzip_member():
    parts = [warc.record_bytes({"WARC-Type": "response", "X": str(k)}, f"block {k}".encode()) for k in range(3)]
    for p in parts:
        assert gzip.decompress(p).startswith(b"WARC/1.1\r\nWARC-Type: response\r\n")
    whole = io.BytesIO(b"".join(parts))
    got = list(warc.records(lambda n: whole.read(min(n, 7))))  # a few bytes at a time
    assert [r.block for r in got] == [b"block 0", b"block 1", b"block 2"]


def test_broken_archives_are_told():
    good = warc.record_bytes({"WARC-Type": "response"}, b"block")
    with pytest.raises(ValueError, match="ends inside"):
        list(warc.records(io.BytesIO(good[:-20]).read))
    rec = warc.Record({"WARC-Type": "response", "WARC-Record-ID": "<urn:page:1>", "WARC-Payload-Digest": "sha256:00"}, b"HTTP/1.1 200 OK\r\nContent-Length: 2\r\n\r\nab")
    assert warc.parse(rec)[-1] is False


def test_odd_rows(spark):
    rows = [(None, None, None, None, None), (1, "u", "z" * 150, None, None), (1, "u", "z" * 150, None, None), (None, "u", "z" * 150, None, None), (5, None, "z" * 150, None, None)]
    out = warc.round_trip(spark.createDataFrame(rows, PAGES)).collect()
    assert len(out) == 5
    kinds = sorted((r.page_id is None, r.page_id or 0, r.record_type, r.refers_to or 0) for r in out)
    assert kinds == [(False, 1, "response", 0), (False, 1, "response", 0), (False, 5, "revisit", 1), (True, 0, "response", 0), (True, 0, "revisit", 1)]
    assert warc.round_trip(spark.createDataFrame([], PAGES)).count() == 0


def test_decisions_carry_no_payload_of_revisits_into_archives(spark, tmp_path):
    made = warc.write(warc.with_decisions(pages(spark, ["q" * 10_000] * 50)).coalesce(1), f"file://{tmp_path}/a")
    assert made.agg(F.sum("n_records")).first()[0] == 50
    raw = b"".join(gzip.decompress(p.read_bytes()) for p in (tmp_path / "a").iterdir())
    assert raw.count(b"q" * 10_000) == 1
