from __future__ import annotations

import gzip
import hashlib
import io
import os
from collections import Counter

import pytest

from kgfeat.llm import warc
from kgfeat.plans.state import Workspace

BIG = "<p>" + "payload é " * 300


def _pages(spark):
    rows = [(i, f"http://h.example/{i}", BIG + str(i % 7)) for i in range(60)] + [(100, None, None), (101, "u\r\nx", ""), (102, "x", "small"), (103, "x", "small"), (104, "y", "z" * 300_000), (59, "again", BIG + "3"), (None, "n", BIG + "0")]
    return rows, spark.createDataFrame([(*r, "d") for r in rows], "page_id long, url string, html string, digest string")


def brute(rows):
    top = {}
    for i, _, h in rows:
        h = (h or "").encode()
        if len(h) >= 1000 and i is not None:
            top[h] = max(i, top.get(h, i))
    out = Counter()
    for i, _, h in rows:
        h = (h or "").encode()
        refers = top.get(h)
        refers = None if refers == i else refers
        out[i, len(h), hashlib.sha1(h).hexdigest(), "response" if refers is None else "revisit", refers] += 1
    return out


def test_round_trip(spark):
    rows, df = _pages(spark)
    got = warc.round_trip(spark, df.repartition(5)).collect()
    assert Counter((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got) == brute(rows)
    assert warc.round_trip(spark, df.limit(0)).count() == 0


def test_one_member_a_record_and_payloads(spark, tmp_path):
    rows, df = _pages(spark)
    ws = Workspace(spark, "w")
    made = warc.write_archives(ws, warc.plan_records(ws, df.coalesce(1)), f"file://{tmp_path}").collect()
    assert len(made) == 1 and not any(f.endswith(".open") for f in os.listdir(tmp_path))
    data = (tmp_path / made[0]["file"]).read_bytes()
    assert data.count(b"\x1f\x8b\x08") >= len(rows) and gzip.decompress(data).count(b"WARC/1.1\r\n") == len(rows)
    recs = list(warc.read_stream(io.BytesIO(data), payloads=True, chunk=97))
    assert len(recs) == len(rows) == made[0]["records"] and all(r["ok"] for r in recs)
    stored = Counter(r["payload"].decode() for r in recs if r["type"] == "response")
    assert stored["z" * 300_000] == 1 and stored["small"] == 2


def test_damage_is_found(spark):
    one = warc.record(1, "u", b"x" * 2000, hashlib.sha1(b"x" * 2000).hexdigest(), None)
    two = warc.record(2, "u", b"y" * 2000, hashlib.sha1(b"wrong").hexdigest(), None)
    assert [r["ok"] for r in warc.read_stream(io.BytesIO(one + two))] == [True, False]
    with pytest.raises(EOFError):
        list(warc.read_stream(io.BytesIO(one + two[:-30])))
    text = gzip.decompress(one).replace(b"xx", b"xy", 1)
    assert not next(warc.read_stream(io.BytesIO(gzip.compress(text))))["ok"]
    short = gzip.decompress(one)[:-100]
    with pytest.raises(EOFError):
        next(warc.read_stream(io.BytesIO(gzip.compress(short))))


@pytest.mark.parametrize("kept", ["page_id", "payload_digest", "record_type"])
def test_damage_fails_whatever_columns_are_kept(spark, tmp_path, monkeypatch, kept):
    path = tmp_path / "one.warc.gz"
    path.write_bytes(warc.record(2, "u", b"y" * 2000, hashlib.sha1(b"wrong").hexdigest(), None))
    made = spark.createDataFrame([(f"file://{path}",)], "path string")
    monkeypatch.setattr(warc, "write_archives", lambda *a, **k: made)
    _, df = _pages(spark)
    with pytest.raises(Exception, match="damaged record of page 2"):
        warc.round_trip(spark, df).select(kept).collect()


def test_urls_and_payloads_of_any_length(spark):
    url = "http://h.example/" + "p" * 2_500_000
    df = spark.createDataFrame([(1, url, "x"), (2, None, "y" * 3_000_000), (2, None, "y" * 3_000_000)], "page_id long, url string, html string")
    got = sorted(((r["page_id"], r["url"], r["payload_bytes"], r["record_type"]) for r in warc.round_trip(spark, df).collect()), key=lambda r: r[0])
    assert got == [(1, url, 1, "response"), (2, "", 3_000_000, "response"), (2, "", 3_000_000, "response")]
