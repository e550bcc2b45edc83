import base64
import gzip
import hashlib
import io
import random

import pytest
from pyspark.sql import functions as F

from windowforge.llm import warc

CRLF = "\r\n"


def expect(rows):
    first = {}
    for i, h in rows:
        h = h or ""
        if i is not None:
            first[h] = min(i, first.get(h, i))
    out = []
    for i, h in rows:
        raw = (h or "").encode()
        keep = first.get(h or "", i)
        later = i is not None and i > keep
        out.append((i if i is not None else -1, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if later else "response", keep if later else None))
    return sorted(out, key=str)


def test_round_trip(spark):
    rng = random.Random(1)
    bodies = ["", None, "é" * 1000, "a\r\n\r\nb", "WARC/1.1\r\nContent-Length: 3\r\n\r\nxyz", "x" * 300_000, "same"]
    rows = [(i, rng.choice(bodies)) for i in range(120)] + [(7, "same"), (None, "same"), (None, None)]
    pages = spark.createDataFrame([(i, f"http://x/ {i}\n", h, "clash") for i, h in rows], "page_id long, url string, html string, value string").withColumn("url", F.when(F.col("page_id") == 3, None).otherwise(F.col("url"))).repartition(4)
    got = sorted(((r.page_id if r.page_id is not None else -1, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.warc_round_trip(pages).collect()), key=str)
    assert got == expect(rows)


def test_small_payloads_stay_whole(spark):
    pages = spark.createDataFrame([(1, "u", "ab"), (2, "u", "ab"), (3, "u", "abc" * 9), (4, "u", "abc" * 9)], "page_id long, url string, html string")
    assert {r.page_id: r.record_type for r in warc.warc_round_trip(pages, dedup_bytes=10).collect()} == {1: "response", 2: "response", 3: "response", 4: "revisit"}


def test_empty_table(spark):
    assert warc.warc_round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def record(body: bytes) -> bytes:
    return f"WARC/1.1{CRLF}WARC-Type: resource{CRLF}WARC-Record-ID: <urn:x-page:1>{CRLF}Content-Length: {len(body)}{CRLF}{CRLF}".encode() + body + b"\r\n\r\n"


def test_normaliser_gives_members_that_stand_alone(tmp_path):
    bodies = [b"", b"abc", bytes(range(256)) * 5000, b"\r\n\r\n\r\n"]
    whole = b"".join(map(record, bodies))
    for name, data in (("one", gzip.compress(whole)), ("two", gzip.compress(whole[:700]) + gzip.compress(whole[700:]))):
        (tmp_path / f"{name}.gz").write_bytes(data)
        n, size = warc.normalise_archive(f"file://{tmp_path}/{name}.gz", f"file://{tmp_path}/out/{name}.warc.gz")
        out = (tmp_path / "out" / f"{name}.warc.gz").read_bytes()
        assert n == 4 and size == len(out) and gzip.decompress(out) == whole
        import json

        for line, body in zip((tmp_path / "out" / f"{name}.warc.gz.idx").read_text().splitlines(), bodies):
            e = json.loads(line)
            assert gzip.decompress(out[e["offset"] : e["offset"] + e["length"]]) == record(body)
    assert not list((tmp_path / "out").glob("*.tmp"))


def test_broken_streams_are_told(tmp_path):
    whole = gzip.compress(record(b"abc" * 1000))
    for data in (whole[: len(whole) // 2], gzip.compress(record(b"abcdef")[:-8])):
        (tmp_path / "x.gz").write_bytes(data)
        with pytest.raises(ValueError):
            warc.normalise_archive(f"file://{tmp_path}/x.gz", f"file://{tmp_path}/y.warc.gz")
    with pytest.raises(ValueError):
        list(warc.split_records(iter([b"HTTP/1.1 200 OK\r\n\r\n"])))
    assert list(warc.split_records(warc.inflated(io.BytesIO(b"")))) == []


def test_padding_and_bombs():

    member = gzip.compress(b"x" * 5_000_000)
    for padded in (member + b"\0" * 3, b"\0" + member + b"\0" * (1 << 20) + member, member + member):
        parts = list(warc.inflated(io.BytesIO(padded), 1 << 16))
        assert max(map(len, parts)) <= 1 << 16 and sum(map(len, parts)) == 5_000_000 * padded.count(b"\x1f\x8b\x08")
    for broken in (member[:-3], member + member[:50]):
        with pytest.raises(ValueError):
            list(warc.inflated(io.BytesIO(broken)))
