import gzip
import hashlib
import io

import compare
import pytest
from pyspark.sql import functions as F

from stagedrel.llm import kernels, oracles, warc
from stagedrel.llm.queries import op2_warc

SF = "/root/testdata/sf0.001"


def test_query_equals_sql(spark):
    assert compare.differs(op2_warc(spark, SF), compare.duck(SF), oracles.WARC) is None


def pages(spark, rows):
    return spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit("clash")).withColumn("digest", F.lit(1))


def test_round_trip_and_revisits(spark):
    big, small = "é" * 600, "s" * 999
    rows = [(1, "u", big), (2, "u", big), (3, None, big), (4, "u", small), (5, "u", small), (6, "u", None), (7, "u", ""), (None, "u", big), (8, "u\r\nx", "x" * 2_000_000), (8, "u\r\nx", "x" * 2_000_000)]
    got = warc.read_archives(spark, warc.write_archives(pages(spark, rows), roll_bytes=2000)).where("status = 'record'").collect()
    assert len(got) == len(rows)
    kind = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"]) for r in got)
    assert [k for k in kind if k[0] in (0, 1, 2)] == [(0, "revisit", 3), (1, "revisit", 3), (2, "revisit", 3)]
    assert all(k[1] == "response" for k in kind if k[0] > 2)
    for r in got:
        want = next((html or "").encode() for i, _, html in rows if i == r["page_id"])
        assert r["payload_digest"] == hashlib.sha1(want).hexdigest() and r["payload_bytes"] == len(want)
        assert bytes(r["payload"]) == (want if r["record_type"] == "response" else b"")


def test_large_ids_beside_a_null_come_back(spark):
    big = 9007199254740993
    rows = [(big, "u", "x" * 2000), (big + 2, "u", "x" * 2000), (None, "u", "x" * 2000), (big + 4, "u", "y"), (-big, "u", None)]
    got = warc.read_archives(spark, warc.write_archives(pages(spark, rows).coalesce(1))).collect()
    assert {(r["page_id"], r["record_type"], r["refers_to"]) for r in got} == {(big, "revisit", big + 2), (None, "revisit", big + 2), (big + 2, "response", None), (big + 4, "response", None), (-big, "response", None)}


def test_records_beyond_the_limit_are_gaps(monkeypatch):
    monkeypatch.setattr(kernels, "MOST_RECORD", 1000)
    for pack in (gzip.compress, bytes):
        parts = [pack(record(1)), pack(record(2, b"z" * 17_000_000)), pack(record(3))]
        assert ids(b"".join(parts), 1 << 16)[0] == [1, 3]


def test_long_and_odd_urls(spark):
    odd = ["data:text/html," + "a" * 200_000, *[f"http://x/{chr(c)}y" for c in (*range(32), 127, 133, 0x2028)], "", " ", "é" * 70_000, "a: b\r\n\r\nWARC/1.1\r\n"]
    rows = [(i, u, f"body {i} " * (200 if i % 2 else 1)) for i, u in enumerate(odd)]
    got = warc.read_archives(spark, warc.write_archives(pages(spark, rows))).collect()
    assert {r["status"] for r in got} == {"record"} and sorted(r["page_id"] for r in got) == list(range(len(rows)))
    uri = {r["page_id"]: r["uri"] for r in got}
    assert uri[0] == odd[0] and uri[1] == "http://x/%00y" and uri[28] == "http://x/%1By" and uri[33] == "http://x/%7Fy"


@pytest.mark.parametrize("pack", [gzip.compress, bytes])
def test_salvage_beside_long_headers(pack):
    long = kernels.record_bytes(7, "data:," + "a" * 200_000, b"x", hashlib.sha1(b"x").hexdigest(), 1, "response", None)
    cut = pack(long)[: len(pack(long)) // 2]
    assert ids(pack(long) + pack(record(1))) == ([7, 1], [])
    assert ids(cut + pack(record(1)) + pack(long)) == ([1, 7], [(0, len(cut))])
    assert ids(pack(record(1)) + cut) == ([1], [(len(pack(record(1))), len(cut))])


def test_empty_table(spark):
    assert warc.read_archives(spark, warc.write_archives(pages(spark, []))).count() == 0


def record(n, body=b"payload"):
    return kernels.record_bytes(n, f"http://x/{n}", body, hashlib.sha1(body).hexdigest(), len(body), "response", None)


def ids(data, block=64):
    out = list(kernels.salvage(io.BytesIO(data), block))
    return [int(x[2]["x-page-id"]) for x in out if x[0] == "record"], [(x[1], x[2]) for x in out if x[0] == "gap"]


@pytest.mark.parametrize("pack", [gzip.compress, bytes])
def test_salvage(pack):
    parts = [pack(record(i, f"body {i} ".encode() * 40)) for i in range(6)]
    whole = b"".join(parts)
    assert ids(whole) == ([0, 1, 2, 3, 4, 5], [])
    at = len(parts[0]) + len(parts[1])
    broken = bytearray(whole)
    mid = at + len(parts[2]) // 2
    broken[mid : mid + 4] = b"\0\0\0\0"
    assert ids(bytes(broken)) == ([0, 1, 3, 4, 5], [(at, len(parts[2]))])
    assert ids(whole[: len(whole) - 5]) == ([0, 1, 2, 3, 4], [(len(whole) - len(parts[5]), len(parts[5]) - 5)])
    junk = b"\x1f\x8b\x08 WARC/1. not one "
    assert ids(junk + parts[0] + junk + parts[1]) == ([0, 1], [(0, len(junk)), (len(junk) + len(parts[0]), len(junk))])
    assert ids(parts[0] + whole[at + 9 :]) == ([0, 3, 4, 5], [(len(parts[0]), len(parts[2]) - 9)])


def test_gaps_are_logged_by_the_reader(spark, tmp_path):
    path = tmp_path / "a.warc.gz"
    path.write_bytes(b"garbage" + gzip.compress(record(1)))
    manifest = spark.createDataFrame([(f"file://{path}",)], "path string")
    got = {r["status"]: r for r in warc.read_archives(spark, manifest).collect()}
    assert got["gap"]["gap_bytes"] == 7 and got["gap"]["reason"] and got["record"]["page_id"] == 1
