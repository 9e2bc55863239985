import base64
import gzip
import hashlib
import re
from collections import Counter

import duckdb
import pyarrow.fs as pafs

from tilerank.llm import registry, warc
from tilerank.llm.common import fresh_path


def brute(rows):
    last = {}
    for p, _, h in rows:
        k = h or ""
        last[k] = max(x for x in (last.get(k), p) if x is not None) if p is not None or last.get(k) is not None else None
    out = Counter()
    for p, _, h in rows:
        b = (h or "").encode()
        n = sum((x[2] or "") == (h or "") for x in rows)
        refers = last[h or ""] if n > 1 and last[h or ""] != p else None
        out[p, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "revisit" if refers is not None else "response", refers] += 1
    return out


EDGE = [
    (1, "http://a.org/x", "same"), (2, "http://a.org/x", "same"), (3, None, "same"), (4, "https://B.a.org:8443/?q=1#f", None), (5, "not a url", ""),
    (6, "http://[bad/", "é" * 300_000), (6, "http://[bad/", "é" * 300_000), (None, "http://a.org/", "same"), (7, "http://a.org/", "\r\n\r\nWARC/1.1\r\n"), (None, "http://x.y/", "only"),
]


def test_round_trip(spark, sf):
    pages = [(r.page_id, r.url, r.html) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    for rows in (pages + [(1000 + i, u, h) for i, (_, u, h) in enumerate(pages[:9])], EDGE):
        df = spark.createDataFrame([(*r, 1) for r in rows], "page_id bigint, url string, html string, length int").repartition(3)
        got = Counter(tuple(r) for r in warc.archive_and_read(df).collect())
        assert got == brute(rows)
    assert warc.archive_and_read(df.limit(0)).count() == 0
    assert {tuple(r) for r in registry.op7_warc(spark, sf).collect()} == set(brute(pages))


def test_index_finds_urls_by_binary_search(spark):
    rows = [(i, f"http://h{i % 7}.example.org/p{i % 50}", f"body {i % 90}") for i in range(700)]
    root = fresh_path(spark, "warc")
    captures = warc.write_archives(spark.createDataFrame(rows, "page_id bigint, url string, html string"), root)
    ranges = warc.write_index(captures, root, block=16)
    reader = warc.Reader(ranges, root)
    for url in {u for _, u, _ in rows}:
        want = [p for p, u, _ in rows if u == url]
        found = reader.url(url)
        assert sorted(c[1] for c in found) == want and all(c[0].startswith("org,example,h") for c in found)
        assert [reader.record(c)["page"] for c in found] == [c[1] for c in found]
    assert reader.url("http://h9.example.org/p1") == [] and reader.page("http://h1.example.org/p1", 9999) == []
    assert sum(len(reader.directory(p)) for _, p in ranges) >= 700 // 16


def test_archives_are_plain_gzip_members(spark):
    root = fresh_path(spark, "warc")
    warc.write_archives(spark.createDataFrame([(1, "http://a/", "x"), (2, "http://a/", "x")], "page_id bigint, url string, html string").coalesce(1), root)
    store, folder = warc.open_store(root)
    data = b"".join(gzip.decompress(store.open_input_stream(f.path, compression=None).read()) for f in store.get_file_info(pafs.FileSelector(folder)))
    assert data.count(b"WARC/1.1\r\nWARC-Type: ") == 2 and b"Refers-To-Page-ID: 2\r\n" in data
    assert data.count(b"HTTP/1.1 200 OK\r\n") == 2 and data.count(b"Content-Type: application/http; msgtype=response") == 2
    ids = re.findall(rb"WARC-Record-ID: (<urn:uuid:[0-9a-f-]{36}>)", data)
    assert len(set(ids)) == 2 and re.findall(rb"WARC-Refers-To: (<urn:uuid:[0-9a-f-]{36}>)", data) == [ids[1]]


def test_pages_with_one_payload_are_dealt_out(spark, monkeypatch):
    rows = [(i, f"http://h{i % 5}/", "hot" if i % 3 else f"own {i // 2}") for i in range(6000)]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    monkeypatch.setattr(warc, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(warc, "RANGE_ROWS", 500)
    got = {r.page_id: r for r in warc.archive_and_read(df).collect()}
    last = {}
    for p, _, h in rows:
        last[h] = p
    assert all(got[p].refers_to == (None if last[h] == p else last[h]) and got[p].payload_bytes == len(h) for p, _, h in rows)
    assert warc.read_pages(df, [], "file:/tmp").rdd.getNumPartitions() == 12


def test_query_equals_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{sf}/pages.parquet'")
    want = sorted(con.execute(registry.ORACLES["op7_warc"]).fetchall())
    assert sorted(tuple(r) for r in registry.op7_warc(spark, sf).collect()) == want
