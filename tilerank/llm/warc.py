"""WARC archives with a two-level capture index.

Writing: each task streams its pages into an archive of its own (a gzip member for each record) in a folder of the shared
file system. A response's block is an HTTP message whose body is the payload; a revisit's block is that message's head. Of pages
with equal payloads the one with the largest id is the response, the others are revisits that name it; which ids those are is
settled first on digests alone, and a digest that very many pages share is joined by broadcast, so that they don't meet in a task.
A record's id is a UUID of page id and payload, so only repeated rows share one.

Index: captures are sorted by range of their key (host labels reversed, then path and query, then the page id); each
range is a file of compressed blocks of BLOCK captures, and beside it a sparse directory with the first key and the place
of each block. Of all that, only the first key of each range reaches the driver.

Reading: keys to look up are sorted by the same order and dealt by range, RANGE_ROWS to a task up to MOST_RANGES tasks; a task
finds the range, then the block in the range's directory, by binary search, reads the block's bytes and then the record's
bytes, no others.

Files are named by task and attempt; an attempt that was lost leaves files that no index row names. They are read
and written through Arrow file systems, so the folder may be in any store that those open.

Defined cases: null html is an empty payload; a null url has an empty key; pages of equal id and payload are
all responses if that id is the largest; null ids are written and come back null, as responses if nothing larger has the payload; an
empty table writes no archive; extra columns are ignored.
"""

from __future__ import annotations

import base64
import bisect
import gzip
import hashlib
import json
import uuid
import zlib
from collections import OrderedDict
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, fresh_path, look_up, materialize

BLOCK, LEVEL, MOST_BYTES = 256, 4, 512 << 20
#: Captures a range of the index has, as long as there are no more than so many ranges; ranges grow beyond.
RANGE_ROWS, MOST_RANGES = 4096, 20_000
#: Sorts before any id; stands for a null one.
NO_ID = -(1 << 63)
INDEX = "key string, page long, path string, offset long, length long"


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1) if uri.startswith("file:") else f"file://{uri}")


def reversed_host_key(url: str | None) -> str:
    """``http://a.b.org:80/x?y#z`` -> ``org,b,a)/x?y``: lower-case host without user, default port or fragment."""
    if not url:
        return ""
    try:
        u = urlsplit(url.strip())
        host, port = (u.hostname or "").rstrip("."), u.port
    except ValueError:
        return url
    tail = f":{port}" if port and port != {"http": 80, "https": 443}.get(u.scheme) else ""
    return f"{','.join(reversed(host.split('.')))}{tail}){u.path or '/'}{'?' + u.query if u.query else ''}"


def full_key(url: str | None, page: int | None) -> str:
    return f"{reversed_host_key(url)} {(NO_ID if page is None else page) - NO_ID:020d}"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int | None, digest: str) -> str:
    return f"<{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page}/sha1:{digest}').urn}>"


def record_bytes(url: str | None, page: int | None, payload: bytes, refers: int | None) -> tuple[bytes, str]:
    """An uncompressed record and its digest."""
    digest = base32_sha1(payload)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    kind, body = ("revisit", http) if refers is not None else ("response", http + payload)
    clean = (url or "").replace("\r", "%0D").replace("\n", "%0A")
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page, digest)}", f"WARC-Target-URI: {clean}",
        "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Block-Digest: sha1:{base32_sha1(body)}",
        "Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}",
    ]
    if page is not None:
        head.append(f"Page-ID: {page}")
    if refers is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers, digest)}", f"Refers-To-Page-ID: {refers}"]
    return "\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + body + b"\r\n\r\n", digest


def parse_record(raw: bytes) -> dict:
    """Header fields and ``payload`` of a gzip member; checks lengths and digests."""
    data = gzip.decompress(raw)
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    h = dict(x.split(": ", 1) for x in lines[1:] if ": " in x)
    body = rest[: int(h["Content-Length"])]
    if lines[0] != "WARC/1.1" or rest[len(body) :] != b"\r\n\r\n" or f"sha1:{base32_sha1(body)}" != h["WARC-Block-Digest"]:
        raise ValueError("broken record")
    message, _, payload = body.partition(b"\r\n\r\n")
    size = int(message.rpartition(b"Content-Length: ")[2])
    if h["WARC-Type"] == "response" and (len(payload) != size or f"sha1:{base32_sha1(payload)}" != h["WARC-Payload-Digest"]):
        raise ValueError("payload does not match its digest")
    number = lambda name: int(h[name]) if name in h else None
    return {
        "id": h["WARC-Record-ID"], "page": number("Page-ID"), "type": h["WARC-Type"], "digest": h["WARC-Payload-Digest"][5:],
        "bytes": size, "refers": number("Refers-To-Page-ID"), "payload": payload if h["WARC-Type"] == "response" else None,
    }


def task_name(prefix: str) -> str:
    t = TaskContext.get()
    return f"{prefix}-{t.stageId() if t else 0}-{t.partitionId() if t else 0}-{t.taskAttemptId() if t else 0}"


def responses(pages: DataFrame, least: int = 0) -> DataFrame:
    """Add ``refers``: the id of the response with the same payload, null for responses. Payloads under ``least`` bytes never refer."""
    payload = F.coalesce("html", F.lit(""))
    keyed = pages.select("page_id", "url", payload.alias("html")).withColumn("d", F.sha1("html"))
    known = keyed.where(F.octet_length("html") >= least).groupBy("d").agg(F.max("page_id").alias("last"), F.count("*").alias("n"))
    shared = materialize(known.where("n > 1"), "payloads")
    size = shared.agg(F.count("*").alias("keys"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows")).first()
    if size["keys"] * 64 <= BROADCAST_BYTES:
        joined = keyed.join(F.broadcast(shared.drop("n")), "d", "left")
    else:
        joined = look_up(keyed, shared, "d", "n", size["rows"], "left")
    return joined.select("page_id", "url", "html", F.when(F.col("last").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("last")), F.col("last")).alias("refers"))


def ranges_for(rows: int) -> int:
    return max(1, min(MOST_RANGES, -(-rows // RANGE_ROWS)))


def write_archives(pages: DataFrame, root: str, least: int = 0) -> DataFrame:
    """Write ``page_id``, ``url``, ``html`` as archives under ``root`` -> captures (INDEX columns), a table of the shared folder."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, folder = open_store(root)
        out, path, at, part = None, "", 0, 0
        try:
            for batch in batches:
                rows = []
                for page, url, html, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    if out is None or at > MOST_BYTES:
                        if out is not None:
                            out.close()
                        path, at, part = f"{folder}/{task_name('pages')}-{part}.warc.gz", 0, part + 1
                        store.create_dir(folder, recursive=True)
                        out = store.open_output_stream(path, compression=None)
                    member = gzip.compress(record_bytes(url, page, html.encode("utf-8", "surrogatepass"), refers)[0], LEVEL, mtime=0)
                    out.write(member)
                    rows.append((full_key(url, page), page, path, at, len(member)))
                    at += len(member)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64()), strict=True)] if rows else [pa.array([], t) for t in (pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64())], names=["key", "page", "path", "offset", "length"])
        finally:
            if out is not None:
                out.close()

    given = responses(pages, least).select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.col("refers").cast("long").alias("refers"))
    return materialize(given.mapInArrow(run, INDEX), "captures")


def write_index(captures: DataFrame, root: str, block: int = BLOCK) -> list[tuple[str, str]]:
    """Sort captures by key into ranges of compressed blocks with a sparse directory each -> (first key, path) of each range."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, folder = open_store(root)
        path = f"{folder}/{task_name('range')}.idx"
        out, at, directory, lines = None, 0, [], []

        def flush() -> None:
            nonlocal out, at
            if out is None:
                store.create_dir(folder, recursive=True)
                out = store.open_output_stream(path, compression=None)
            packed = zlib.compress("\n".join(json.dumps(x) for x in lines).encode(), LEVEL)
            out.write(packed)
            directory.append((lines[0][0], at, len(packed)))
            at += len(packed)
            lines.clear()

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                lines.append(row)
                if len(lines) == block:
                    flush()
        if lines:
            flush()
        if out is not None:
            out.close()
            with store.open_output_stream(f"{path}.dir", compression=None) as f:
                f.write(zlib.compress(json.dumps(directory).encode(), LEVEL))
            yield pa.RecordBatch.from_arrays([pa.array([directory[0][0]]), pa.array([path])], names=["first", "path"])

    ordered = captures.select("key", "page", "path", "offset", "length").repartitionByRange(ranges_for(captures.count()), "key").sortWithinPartitions("key", "path", "offset")
    ranges = materialize(ordered.mapInArrow(run, "first string, path string"), "ranges")
    return sorted((r.first, r.path) for r in ranges.collect())  # a row for each range of the index


class Reader:
    """Looks keys up: range, then block, by binary search; keeps the last blocks and directories."""

    def __init__(self, ranges: list[tuple[str, str]], root: str, keep: int = 8):
        self.store, _ = open_store(root)
        self.ranges, self.firsts, self.keep = ranges, [f for f, _ in ranges], keep
        self.directories: OrderedDict = OrderedDict()
        self.blocks: OrderedDict = OrderedDict()
        self.files: OrderedDict = OrderedDict()

    def cached(self, cache: OrderedDict, key, make):
        if key not in cache:
            cache[key] = make()
            if len(cache) > self.keep:
                cache.popitem(last=False)
        cache.move_to_end(key)
        return cache[key]

    def bytes_at(self, path: str, offset: int, length: int) -> bytes:
        f = self.cached(self.files, path, lambda: self.store.open_input_file(path))
        return f.read_at(length, offset)

    def directory(self, path: str) -> list:
        def load():
            with self.store.open_input_stream(f"{path}.dir", compression=None) as f:
                return json.loads(zlib.decompress(f.read()))

        return self.cached(self.directories, path, load)

    def block(self, path: str, offset: int, length: int) -> list:
        return self.cached(self.blocks, (path, offset), lambda: [json.loads(x) for x in zlib.decompress(self.bytes_at(path, offset, length)).split(b"\n")])

    def captures(self, low: str, high: str) -> Iterator[tuple]:
        """Captures with low <= key < high, in order."""
        r = max(0, bisect.bisect_left(self.firsts, low) - 1)
        while r < len(self.ranges) and self.firsts[r] < high:
            entries = self.directory(self.ranges[r][1])
            b = max(0, bisect.bisect_left([e[0] for e in entries], low) - 1)
            while b < len(entries) and entries[b][0] < high:
                for row in self.block(self.ranges[r][1], *entries[b][1:]):
                    if low <= row[0] < high:
                        yield tuple(row)
                b += 1
            r += 1

    def page(self, url: str | None, page: int | None) -> list[tuple]:
        key = full_key(url, page)
        return list(self.captures(key, key + "\0"))

    def url(self, url: str) -> list[tuple]:
        """All captures of a URL."""
        key = reversed_host_key(url) + " "
        return list(self.captures(key, key[:-1] + "!"))

    def record(self, capture: tuple) -> dict:
        return parse_record(self.bytes_at(*capture[2:5]))


def read_pages(wanted: DataFrame, ranges: list[tuple[str, str]], root: str) -> DataFrame:
    """``page_id``, ``url`` -> a row for each of them with what its archived record says.

    Several pages with the same key are read in the order of their records.
    """
    shared = wanted.sparkSession.sparkContext.broadcast(ranges)
    types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader, last, again = Reader(shared.value, root), None, 0
        for batch in batches:
            rows = []
            for page, url in zip(batch.column("page_id").to_pylist(), batch.column("url").to_pylist(), strict=True):
                found = reader.page(url, page)
                again = again + 1 if (page, url) == last else 0
                last = (page, url)
                r = reader.record(found[again % len(found)])
                rows.append((r["page"], r["bytes"], r["digest"], r["type"], r["refers"]))
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=names)

    # pages of one host follow each other in the index; dealt by range so that a task reads neighbouring blocks
    keyed = wanted.select(F.col("page_id").cast("long").alias("page_id"), "url", reversed_host_column("url").alias("host"))
    ordered = keyed.repartitionByRange(ranges_for(wanted.count()), "host", "url", "page_id").sortWithinPartitions("host", "url", "page_id").select("page_id", "url")
    return ordered.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def reversed_host_column(url: str):
    """The host's labels reversed, for dealing out only."""
    host = F.lower(F.regexp_extract(url, "^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]*)", 1))
    return F.array_join(F.reverse(F.split(host, "[.]")), ",")


def archive_and_read(pages: DataFrame, least: int = 0) -> DataFrame:
    """Write the pages as archives with their index in the shared folder, then read every page back through the index."""
    root = fresh_path(pages.sparkSession, "warc")
    ranges = write_index(write_archives(pages, root, least), root)
    return read_pages(pages, ranges, root)
