import base64
import gzip
import hashlib
import heapq
import random
import zlib

import duckdb
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from digitsort.llm import ogg, queries, url_rules, warc

from .conftest import ODD


def slow_checksum(data: bytes) -> int:
    crc = 0
    for b in data:
        crc ^= b << 24
        for _ in range(8):
            crc = (crc << 1 ^ 0x04C11DB7) & 0xFFFFFFFF if crc & 0x80000000 else crc << 1 & 0xFFFFFFFF
    return crc


@given(st.binary(max_size=300))
@settings(max_examples=50, deadline=None)
def test_checksum(data):
    assert ogg.page_checksum(data) == slow_checksum(data)


@pytest.mark.parametrize("n", [0, 1, 191, 192, 193, 1920, 1921, 50_000, 200_001])
def test_ogg_round_trip(n):
    payload = ogg.padded(random.Random(n).randbytes(n))
    assert len(payload) % 192 == 0 and len(payload) > 0
    media = ogg.write_ogg(payload)
    back, feature, status = ogg.read_samples(media)
    assert (back, status) == (payload, "ok") and f"end_us={len(payload) * 125}" in feature
    streams = ogg.read_ogg(media)
    assert len(streams) == 2 and len({s.serial for s in streams}) == 2
    assert ogg.packet_ends(streams[0])[-1] == len(payload)


def test_packets_cross_pages():
    streams = ogg.read_ogg(ogg.write_ogg(bytes(200_064)))
    assert streams[0].pages > 3 and max(map(len, streams[0].packets)) == 1920


def test_broken_media():
    media = ogg.write_ogg(ogg.padded(b"some payload" * 900))
    flipped = bytearray(media)
    flipped[len(media) // 2] ^= 1
    assert ogg.read_samples(bytes(flipped))[2] == "bad_checksum"
    assert ogg.read_samples(media[:-5])[2] == "cut_short"
    assert ogg.read_samples(b"RIFF" + media)[2] == "no_capture_pattern"
    assert ogg.read_samples(b"")[2] == "no_stream"
    assert ogg.read_samples(None) == (None, "", "null")


def test_ogg_columns(spark):
    rows = [(i, None if t is None else t.encode()) for i, t in ODD]
    df = spark.createDataFrame(rows, "doc_id long, payload binary").selectExpr("*", "'x' AS media", "1 AS status")
    out = ogg.decode_media(ogg.encode_media(df, "payload"), keep=("doc_id",)).collect()
    assert [bytes(r["payload"]) for r in out] == [ogg.padded(p) for _, p in rows] and {r["status"] for r in out} == {"ok"}
    assert ogg.encode_media(df.limit(0), "payload").count() == 0


# WARC


def expected(rows):
    first = {}
    for i, _, html in rows:
        key = (html or "").encode()
        if i is not None and (key not in first or i < first[key]):
            first[key] = i
    out = []
    for i, url, html in rows:
        p = (html or "").encode()
        ref = first.get(p)
        ref = None if ref is None or ref == i else ref
        out.append((i, url, len(p), base64.b32encode(hashlib.sha1(p).digest()).decode(), "response" if ref is None else "revisit", ref))
    return sorted(out, key=repr)


PAGES = [(3, "http://B.example.com/x?q#f", "same"), (1, "https://a.example.com/", "same"), (2, None, None), (9, "", ""), (4, "no scheme", "other é"), (4, "no scheme", "other é"), (None, "http://n.example.com", "same"), (None, "http://n.example.com", "alone"), (7, "http://c.example.com/" + "p" * 5000, "x" * 300_000), (8, "http://a.example.com/\r\nX: y", "\r\n\r\nWARC/1.1\r\n")]


def test_warc_round_trip(spark, tmp_path):
    df = spark.createDataFrame(PAGES, "page_id long, url string, html string").selectExpr("*", "1 AS data", "2 AS archive", "3 AS sha").repartition(3)
    archives = warc.write_archives(df)
    found = warc.read_archives(archives).collect()
    assert sorted([(r["id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in found], key=repr) == sorted([(x[0], *x[2:]) for x in expected(PAGES)], key=repr)
    index = warc.merge_index(warc.read_archives(archives), ranges=3)
    merged = index.orderBy("position").collect()
    keys = [((r["id"] is not None, r["id"] or 0), r["archive"], r["offset"]) for r in merged]
    order = [(r["url_key"], r["time"], *k) for r, k in zip(merged, keys, strict=True)]
    assert order == sorted(order) and [r["position"] for r in merged] == list(range(len(PAGES)))
    names = warc.export_files(archives, str(tmp_path))
    assert sum(gzip.open(n).read().count(b"WARC-Record-ID: ") for n in names) == len(PAGES)
    assert warc.capture_history(index).agg({"captures": "sum"}).first()[0] == len(PAGES)


def test_revisits_leave_their_payloads(spark):
    rows = [(k, "http://a", "copy" * 500) for k in range(300)] + [(k, "http://b", f"own {k}") for k in range(300, 400)] + [(None, "http://c", "no id")] * 3
    out = warc.with_revisits(spark.createDataFrame(rows, "page_id long, url string, html string"), "page_id", "url", "html").collect()
    assert len(out) == len(rows) and all(r["payload"] is not None for r in out if r["refers_to"] is None)
    assert {r["id"] for r in out if r["refers_to"] == 0} == set(range(1, 300))
    assert sum(r["payload"] is not None for r in out if r["refers_to"] == 0) < 30  # moved by a filter's mistake


def test_warc_query_whole_table(spark, sf):
    pages = [(r["page_id"], r["url"], r["html"]) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    got = queries.op1_warc_index(spark, sf).select("page_id", "url_key", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()
    want = [(x[0], warc.url_key(x[1]), *x[2:]) for x in expected(pages)]
    assert sorted(map(tuple, got), key=repr) == sorted(want, key=repr)


def test_ogg_query_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    want = []
    for r in docs:
        raw = (r["text"] or "").encode()
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        media = ogg.write_ogg(payload)
        want.append((r["doc_id"], len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest()))
    got = queries.op10_ogg(spark, sf).select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_warc_empty(spark):
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc.merge_index(warc.read_archives(warc.write_archives(none))).count() == 0


def test_broken_record():
    good = warc.record(1, "http://a", "2024-01-01T00:00:00Z", b"abc", None, warc.digest(b"abc"))
    assert warc.parse(gzip.compress(good))["payload"] == b"abc"
    for bad in (good.replace(b"abc", b"abd"), good[:-6], b"junk\r\n\r\n"):
        with pytest.raises((ValueError, KeyError, StopIteration)):
            warc.parse(gzip.compress(bad))


@given(st.lists(st.lists(st.integers(0, 50), max_size=30), max_size=12))
@settings(max_examples=80, deadline=None)
def test_loser_tree_merges(runs):
    blocks = []
    for r, run in enumerate(runs):
        run = [((v, r, k), (r, k)) for k, v in enumerate(sorted(run))]
        blocks += [run[k : k + 4] for k in range(0, len(run), 4)]
    blocks.sort(key=lambda b: b[0][0])
    got = [x[0] for x in warc.merge_blocks(iter((b[0][0], lambda b=b: b) for b in blocks))]
    assert got == list(heapq.merge(*[[x[0] for x in b] for b in blocks]))


# URLs


def verdict(url, rules):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    cut = min((k for k in (rest.find(c) for c in "/?#") if k >= 0), default=len(rest))
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut])
    tail = rest[cut:]
    end = min((k for k in (tail.find(c) for c in "?#") if k >= 0), default=len(tail))
    path = tail[:end]
    fit = [(len(h + p), len(h), v, h + p) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fit, default=None)
    return host, path, best and best[3], best[2] if best else "allow"


URLS = ["http://www.Example.COM/en/7?x", "https://example.com/en/", "ftp://com/en/x#y", "http://a.b.net/de/8", "http://example.net/de/81", "http://xexample.net/de/81", "http://example.org/es", "http://example.org/es/#", None, "", "no scheme", "http://", "http:///en/", "://com/en/", "http://com?/en/", "http://example.com/en/7://x", "http://É.com/en/\n7"]


@pytest.mark.parametrize("limit", [100_000, 0])
def test_url_rules(spark, monkeypatch, limit):
    monkeypatch.setattr(url_rules, "BROADCAST_RULES", limit)
    rules = [*queries.URL_RULES, ("com", "/en/", "block"), ("com", "/en/", "allow"), (None, "/", "block")]
    rows = [(k % 14, u) for k, u in enumerate(URLS)] + [(1, URLS[1])] * 3 + [(None, URLS[0])]
    df = spark.createDataFrame(rows, "page_id long, url string").selectExpr("*", "1 AS host", "2 AS rule", "3 AS _id")
    got = url_rules.judge(df, spark.createDataFrame(rules, "host string, path string, verdict string")).collect()
    want = [(i, *verdict(u, [r for r in rules if r[0]])) for i, u in rows]
    assert sorted(map(tuple, got), key=repr) == sorted(want, key=repr)
    none = spark.createDataFrame([], "host string, path string, verdict string")
    assert {r["verdict"] for r in url_rules.judge(df, none, default="block").collect()} == {"block"}
    assert url_rules.judge(df.limit(0), none).count() == 0


def test_url_query_against_duckdb(spark, sf):
    c = duckdb.connect()
    c.execute(f"create view pages as select * from '{sf}/pages.parquet'")
    want = sorted(c.execute(queries.OP3_SQL).fetchall(), key=repr)
    assert sorted(map(tuple, queries.op3_url_rules(spark, sf).select("page_id", "host", "path", "rule", "verdict").collect()), key=repr) == want


def test_url_plan_is_native(spark, sf):
    plan = queries.op3_url_rules(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan
