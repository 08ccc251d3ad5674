from __future__ import annotations

import base64
import gzip
import hashlib

import pytest
from pyspark.sql import functions as F

from levelmine.llm import warc
from levelmine.session import scratch_path

SCHEMA = "page_id long, url string, html string, payload string, sha string, first long"
ROWS = [(5, "http://a/é b", "<p>one</p>"), (2, "http://b", "<p>one</p>"), (9, "http://c", "<p>one</p>"), (3, None, None), (4, "http://d", ""), (7, "http://e", "x" * 100_000), (8, "http://f\r\nEvil: 1", "\r\n\r\nü" * 50), (None, "http://g", "<p>one</p>"), (None, "http://h", "alone"), (11, "http://i", "z"), (11, "http://i", "z")]


def frame(spark, rows=ROWS):
    return spark.createDataFrame([(*r, "p", "s", 1) for r in rows], SCHEMA).repartition(3)


def digest(text):
    return base64.b32encode(hashlib.sha1((text or "").encode()).digest()).decode()


def expected(rows, least=0):
    first = {}
    for i, _, h in rows:
        if i is not None:
            first[h or ""] = min(first.get(h or "", i), i)
    out = []
    for i, _, h in rows:
        n, f = len((h or "").encode()), first.get(h or "")
        again = n >= least and f is not None and f != i
        out.append((i, n, digest(h), "revisit" if again else "response", f if again else None))
    return sorted(out, key=str)


@pytest.mark.parametrize("least", [0, 5])
def test_round_trip(spark, least):
    assert sorted(map(tuple, warc.round_trip(frame(spark), least).collect()), key=str) == expected(ROWS, least)


def test_empty_table(spark):
    assert warc.round_trip(frame(spark).limit(0)).count() == 0


@pytest.fixture(scope="module")
def archive(spark):
    path = scratch_path(spark, "test-warc")
    warc.write_pages(frame(spark), path)
    return path


def test_payloads_and_headers_come_back(spark, archive):
    got = {r["page_id"]: r for r in spark.read.format("warc").load(archive).collect() if r["page_id"] is not None}
    html = {i: (h or "") for i, _, h in ROWS if i is not None}
    for i, r in got.items():
        assert r["payload"] is None if r["record_type"] == "revisit" else bytes(r["payload"]).decode() == html[i]
    assert got[5]["target_uri"] == "http://a/é b" and got[8]["target_uri"] == "http://f Evil: 1" and got[3]["target_uri"] is None


def test_filters_are_pushed_down(spark, archive):
    df = spark.read.format("warc").load(archive).filter("record_type = 'revisit' and page_id > 5").select("page_id")
    assert [r[0] for r in df.collect()] == [9]
    assert spark.read.format("warc").load(archive).filter(F.col("payload_bytes").isin(0, 1)).count() == 4


def test_skipped_payloads_are_not_inflated(archive, monkeypatch):
    reader = warc.WarcReader({"path": archive, "payload": "false"}, _schema())
    opened = []
    monkeypatch.setattr(warc, "_payload", lambda *a: opened.append(a) or b"")
    rows = sum(b.num_rows for p in reader.partitions() for b in reader.read(p))
    assert rows == len(ROWS) and not opened


def _schema():
    from pyspark.sql.types import _parse_datatype_string

    return _parse_datatype_string(warc.SCHEMA)


def test_archives_of_others_are_read(spark, tmp_path):
    records = [warc.record_bytes("response", i, "http://x", b"body %d" % i, warc.base32_sha1(b"body %d" % i), None) for i in range(5)]
    (tmp_path / "plain.warc").write_bytes(b"".join(records))
    (tmp_path / "members.warc.gz").write_bytes(b"".join(gzip.compress(r) for r in records))
    got = spark.read.format("warc").option("verify", "true").load(f"file://{tmp_path}").collect()
    assert sorted((r["page_id"], bytes(r["payload"])) for r in got) == sorted((i, b"body %d" % i) for i in range(5) for _ in range(2))


def test_a_changed_payload_is_noticed(spark, tmp_path):
    bad = warc.record_bytes("response", 1, "http://x", b"body", warc.base32_sha1(b"other"), None)
    (tmp_path / "bad.warc").write_bytes(bad)
    with pytest.raises(Exception, match="another digest"):
        spark.read.format("warc").option("verify", "true").load(f"file://{tmp_path}").collect()


def test_filters_on_what_other_writers_headers_lack(spark, tmp_path):
    warc.register(spark)
    records = [warc.record_bytes("response", i, "http://x", b"b" * i, warc.base32_sha1(b"b" * i), None) for i in range(6)]
    bare = [b"\r\n".join(line for line in r.split(b"\r\n") if not line.lower().startswith((b"x-payload-length", b"warc-payload-digest"))) for r in records]
    assert all(len(a) < len(b) for a, b in zip(bare, records, strict=True))
    (tmp_path / "bare.warc").write_bytes(b"".join(bare))
    rows = spark.read.format("warc").load(f"file://{tmp_path}")
    assert sorted(r["page_id"] for r in rows.filter("payload_bytes > 3").collect()) == [4, 5]
    assert [r["page_id"] for r in rows.filter(F.col("payload_digest") == warc.base32_sha1(b"bb")).select("page_id", "payload_digest").collect()] == [2]
    assert rows.filter("payload_bytes is null").count() == 0
