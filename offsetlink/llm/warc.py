"""WARC archives with a two-level capture index.

Archives are gzip members, one record each, written next to one another in files of the shared store.  The index sorts
captures by reversed-host URL key into compressed blocks; each index file has a sparse directory of its blocks, and the
first keys of the files (as many as the index has files) are the level above.  A lookup searches both levels by
bisection, reads one block, and reads one byte range of one archive.
"""

from __future__ import annotations

import base64
import bisect
import gzip
import hashlib
import json
import re
import zlib
from urllib.parse import quote, urlsplit

import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from offsetlink.llm import common

BLOCK_ROWS = 256
DATE = "1970-01-01T00:00:00Z"
CAPTURE = "url_key string, page_id long, record_type string, archive string, offset long, length long"
READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, payload binary"


def url_key(url: str | None) -> str:
    """Reversed host, then path and query: ``http://www.a.org/x?y`` is ``org,a,www)/x?y``.  Null gives ``)``.

    Scheme, user, fragment and default port don't count; white space and control characters are percent-encoded.
    """
    if not url:
        return ")"
    try:
        u = urlsplit(url if "//" in url else f"//{url}")
        host, port = (u.hostname or ""), u.port
    except ValueError:
        return ")" + quote(url, safe="/?&=%:;,@!~*'()+$-_.")
    head = ",".join(reversed(host.split("."))) + (f":{port}" if port and port not in (80, 443) else "")
    tail = (u.path or "/") + (f"?{u.query}" if u.query else "")
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", f"{head}){tail}")


def base32(hexed: str) -> str:
    return base64.b32encode(bytes.fromhex(hexed)).decode()


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, kind: str, first: int | None) -> bytes:
    """One gzip member with one record; a revisit keeps the response's headers and no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + (payload if kind == "response" else b"")
    lines = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:x-page:{'' if page_id is None else page_id}>", f"WARC-Date: {DATE}",
        f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http;msgtype=response",
    ]
    if url is not None:
        lines.append("WARC-Target-URI: " + re.sub(r"[\r\n]", lambda m: f"%{ord(m[0]):02X}", url))
    if kind == "revisit":
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:x-page:{first}>"]
    head = "\r\n".join([*lines, f"Content-Length: {len(block)}", "", ""]).encode("utf-8", "surrogatepass")
    return gzip.compress(head + block + b"\r\n\r\n", compresslevel=4, mtime=0)


def parse(member: bytes) -> dict:
    """The fields and payload of one record."""
    raw = gzip.decompress(member)
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = dict(x.split(": ", 1) for x in head.decode("utf-8", "surrogatepass").split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    length = int(re.search(rb"Content-Length: (\d+)", http)[1])
    number = lambda x: int(d[0]) if x and (d := re.search(r"-?\d+", x)) else None
    digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
    if fields["WARC-Type"] == "response" and base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
        raise ValueError(f"damaged record {fields['WARC-Record-ID']}")
    return {
        "page_id": number(fields["WARC-Record-ID"]), "payload_bytes": length, "payload_digest": digest, "record_type": fields["WARC-Type"],
        "refers_to": number(fields.get("WARC-Refers-To")), "url": fields.get("WARC-Target-URI"), "payload": payload if fields["WARC-Type"] == "response" else None,
    }


def _store(root: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(re.sub("^file:/+", "file:///", root))


class _Output:
    """A file that appears under its name only when whole; a second attempt replaces it with the same bytes."""

    def __init__(self, root: str, name: str) -> None:
        self.fs, top = _store(root)
        self.path = f"{top}/{name}"
        self.temp = f"{top}/.{name}.{TaskContext.get().taskAttemptId()}"
        self.fs.create_dir(top, recursive=True)
        self.out, self.at = self.fs.open_output_stream(self.temp, compression=None), 0

    def write(self, data: bytes) -> tuple[int, int]:
        self.out.write(data)
        self.at += len(data)
        return self.at - len(data), len(data)

    def close(self) -> None:
        self.out.close()
        try:
            self.fs.move(self.temp, self.path)
        except OSError:  # some stores don't replace a file
            self.fs.delete_file(self.path)
            self.fs.move(self.temp, self.path)


def _written(batches, root: str):
    name, out = f"part-{TaskContext.get().partitionId():06d}.warc.gz", None
    for b in batches:
        rows = []
        for page_id, url, html, hexed, first in zip(*(b.column(n).to_pylist() for n in ("page_id", "url", "html", "hexed", "first_id")), strict=True):
            out = out or _Output(root, name)
            kind = "response" if page_id == first else "revisit"
            rows.append((url_key(url), page_id, kind, name, *out.write(record(page_id, url, html or b"", base32(hexed), kind, first))))
        if rows:
            yield _batch(rows, CAPTURE)
    if out:
        out.close()


def _batch(rows: list[tuple], ddl: str) -> pa.RecordBatch:
    kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
    fields = [x.split() for x in ddl.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(x, kinds[k]) for x, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def write_archives(pages: DataFrame, root: str, min_bytes: int = 0) -> DataFrame:
    """Write a record for each row under root; returns the captures (where each record lies).

    Of rows with equal payloads of min_bytes or more, those with the smallest page_id (nulls last) become responses and
    the others revisits.  Null html is an empty payload.  Repeated rows each get a record; of equal payloads and equal
    smallest ids all are responses.  Rows are sorted within a task, so that a task run again writes the same bytes.
    """
    common.bound_batches(pages.sparkSession)
    data = pages.select("page_id", "url", F.coalesce(F.encode("html", "UTF-8"), F.lit(b"")).alias("html")).withColumn("hexed", F.sha1("html"))
    firsts = pages.select(F.sha1(F.coalesce(F.encode("html", "UTF-8"), F.lit(b""))).alias("hexed"), "page_id").groupBy("hexed").agg(F.min("page_id").alias("low_id"))
    joined = data.join(firsts, "hexed")
    own = F.length("html") < F.lit(min_bytes)
    rows = joined.select("page_id", "url", "html", "hexed", F.when(own, F.col("page_id")).otherwise(F.col("low_id")).alias("first_id"))
    return common.cut(rows.sortWithinPartitions("page_id", "url", "hexed").mapInArrow(lambda batches: _written(batches, f"{root}/archive"), CAPTURE), "captures")


def _indexed(batches, root: str, block_rows: int):
    name, out, pending, directory, seen = f"index-{TaskContext.get().partitionId():06d}", None, [], [], []

    def flush():
        offset, length = out.write(zlib.compress("\n".join(json.dumps(r) for r in pending).encode(), 6))
        directory.append([pending[0][:2], offset, length])
        pending.clear()

    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            row = (row[0], row[1] if row[1] is not None else -(1 << 63), *row[2:])
            out = out or _Output(root, name)
            seen = [seen[0] if seen else row[:2], row[:2]]
            pending.append(row)
            if len(pending) == block_rows:
                flush()
    if out:
        if pending:
            flush()
        out.close()
        d = _Output(root, f"{name}.directory")
        d.write(json.dumps(directory).encode())
        d.close()
        yield _batch([(name, *seen[0], *seen[1], len(directory))], TOP)


TOP = "name string, first_key string, first_id long, last_key string, last_id long, n_blocks long"


def write_index(captures: DataFrame, root: str, block_rows: int = BLOCK_ROWS) -> list[tuple]:
    """Sort captures into index files under root; returns the top level, one row per index file, in order.

    The top level has as many rows as there are shuffle partitions, whatever the data's size.  A key with very many
    captures may span files, as (key, page_id) is the sort order.
    """
    n = common.partitions(captures.sparkSession)
    ordered = captures.repartitionByRange(n, "url_key", "page_id").sortWithinPartitions("url_key", "page_id", "archive", "offset")
    top = ordered.mapInArrow(lambda batches: _indexed(batches, f"{root}/index", block_rows), TOP).collect()
    return sorted(((r.first_key, r.first_id), (r.last_key, r.last_id), r.name) for r in top)


class Index:
    """Reads captures by key from the files of an index."""

    def __init__(self, root: str, top: list[tuple]) -> None:
        self.fs, self.root = _store(root)
        self.top, self.lasts = top, [tuple(t[1]) for t in top]
        self.files, self.directory, self.block = {}, (None, None, None), (None, None)

    def read(self, name: str, offset: int, length: int) -> bytes:
        if name not in self.files:
            if len(self.files) >= 64:
                self.files.pop(next(iter(self.files))).close()
            self.files[name] = self.fs.open_input_file(f"{self.root}/{name}")
        return self.files[name].read_at(length, offset)

    def _blocks(self, name: str) -> tuple[list, list]:
        if self.directory[0] != name:
            with self.fs.open_input_stream(f"{self.root}/index/{name}.directory", compression=None) as f:
                blocks = json.loads(f.read())
            self.directory = (name, [tuple(b[0]) for b in blocks], blocks)
        return self.directory[1:]

    def captures(self, key: str, page_id: int | None = None):
        """The captures of a key, or the one with that page_id too."""
        low = (key, -(1 << 63)) if page_id is None else (key, page_id)
        high = (key, (1 << 63) - 1) if page_id is None else low
        for first, _, name in self.top[bisect.bisect_left(self.lasts, low) :]:
            if tuple(first) > high:
                return
            firsts, blocks = self._blocks(name)
            for at in range(max(0, bisect.bisect_left(firsts, low) - 1), len(blocks)):
                if firsts[at] > high:
                    break
                if self.block[0] != (name, at):
                    rows = [json.loads(x) for x in zlib.decompress(self.read(f"index/{name}", *blocks[at][1:])).decode().split("\n")]
                    self.block = ((name, at), rows, [tuple(r[:2]) for r in rows])
                rows, keys = self.block[1:]
                for row in rows[bisect.bisect_left(keys, low) :]:
                    if tuple(row[:2]) > high:
                        break
                    yield row


def _looked_up(batches, root: str, top: list[tuple]):
    index, names = Index(root, top), [x.split()[0] for x in READ.split(", ")]
    for b in batches:
        rows, size = [], 0
        for key, page_id in zip(b.column("url_key").to_pylist(), b.column("page_id").to_pylist(), strict=True):
            for row in index.captures(key, -(1 << 63) if page_id is None else page_id):
                found = parse(index.read(f"archive/{row[3]}", row[4], row[5]))
                rows.append(tuple(found[n] for n in names))
                size += len(found["payload"] or b"")
                if size > 4_000_000:
                    yield _batch(rows, READ)
                    rows, size = [], 0
        if rows:
            yield _batch(rows, READ)


def _keys(batches):
    for b in batches:
        yield pa.RecordBatch.from_arrays([pa.array([url_key(u) for u in b.column("url").to_pylist()], pa.string()), b.column("page_id")], names=["url_key", "page_id"])


def lookup(requests: DataFrame, root: str, top: list[tuple]) -> DataFrame:
    """The records of requests (url, page_id), read from the archives by way of the index.

    Requests are sorted like the index, so that a task reads each block once.  Repeated requests count once.
    """
    common.bound_batches(requests.sparkSession)
    n = common.partitions(requests.sparkSession)
    keys = requests.select("url", "page_id").mapInArrow(_keys, "url_key string, page_id long").distinct()
    return keys.repartitionByRange(n, "url_key", "page_id").sortWithinPartitions("url_key", "page_id").mapInArrow(lambda batches: _looked_up(batches, root, top), READ)


def archive_pages(spark: SparkSession, pages: DataFrame, root: str, min_bytes: int = 0) -> list[tuple]:
    return write_index(write_archives(pages, root, min_bytes), root)


def op10_warc(spark, sf_dir: str) -> DataFrame:
    pages = common.read(spark, sf_dir, "pages")
    root = common.new_folder(spark, "warc")
    top = archive_pages(spark, pages, root)
    return lookup(pages, root, top).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


# Base 32 of the digest, four characters for each five hex digits; its letters are the fixed values of the format.
ORACLE_OP10 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, strlen(h) AS n, sha1(h) AS x, min(page_id) OVER (PARTITION BY h) AS first FROM p),
v AS (SELECT *, list_transform(range(0, 8), lambda i: CAST('0x' || substr(x, i * 5 + 1, 5) AS BIGINT)) AS parts FROM d)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(parts, lambda v: array_to_string(list_transform([15, 10, 5, 0], lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((v >> k) & 31) + 1, 1)), '')), '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to
FROM v"""
