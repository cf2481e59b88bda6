"""Operator 4, WARC archives with a two-level capture index.

Writing: each task writes its pages as gzip members of one archive in the shared folder, a response or a revisit each, and reports place and
length. File names are unique to the attempt and only those that the committed capture table names are ever read, so a
task that is lost or run twice leaves at worst an unused file. Of equal payloads the one with the largest page_id is the response; that
is a maximum by digest with a partial aggregate, joined back on light rows, so a payload shared by a third of the pages never gathers its
bodies in one task.

Index: captures are sorted by reversed-host URL key over all partitions and packed, BLOCK lines at a time, into zlib blocks; the
sparse directory holds the first and last key of each block. A look-up reads the directory rows that can hold the key, bisects the
lines of those blocks, and reads the byte range of each capture.

Reading: the blocks give every capture; captures are ordered by file and offset, and each is read by its range, unpacked and parsed.

Defined cases: null html is an empty payload; equal empty payloads revisit as others do. A null url has no target line and the key "-".
A null page_id is a response of its own with a random record id. Rows that repeat a page_id with one payload are written each with the
same type. Of equal payloads the largest page_id is the response, so ties are between repeated rows alone. Payloads of any length are written whole.
Empty tables give an empty index and no rows. Other columns are not read.
"""

from __future__ import annotations

import base64
import bisect
import hashlib
import re
import uuid
import zlib
from collections import OrderedDict
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, pieces, stored, table

#: Names and formats of WARC 1.1.
VERSION = b"WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"

DATE, BLOCK, LEVEL = "2024-01-01T00:00:00Z", 1000, 4
_ID = re.compile(r"<urn:page:(-?\d+)>")


def file_system(uri: str):
    """pyarrow's file system and path of a URI in the shared folder."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def url_key(url: str | None) -> str:
    """Host labels reversed, then the path: com,example,www)/a?b."""
    if not url:
        return "-"
    try:
        parts = urlsplit(url.strip())
        host, port = parts.hostname or "", f":{parts.port}" if parts.port else ""
    except ValueError:
        return url.strip().lower()
    return ",".join(reversed(host.split("."))) + port + ")" + (parts.path or "/") + (f"?{parts.query}" if parts.query else "")


def sha1_32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str = DATE) -> bytes:
    """One record, not yet compressed."""
    revisit = refers_to is not None
    block = HTTP if revisit else HTTP + payload
    head = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", f"<urn:page:{page_id}>" if page_id is not None else f"<urn:uuid:{uuid.uuid4()}>"), ("WARC-Date", date)]
    if url is not None:
        head.append(("WARC-Target-URI", re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)))
    if revisit:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", f"<urn:page:{refers_to}>")]
    head += [("WARC-Payload-Digest", f"sha1:{sha1_32(payload)}"), ("X-Payload-Length", str(len(payload))), ("Content-Type", "application/http;msgtype=response"), ("Content-Length", str(len(block)))]
    return VERSION + b"\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and block of an uncompressed record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    first, *lines = head.split(b"\r\n")
    if not first.startswith(b"WARC/"):
        raise ValueError("not a WARC record")
    headers = {k.strip().decode(): v.strip().decode() for k, _, v in (x.partition(b":") for x in lines)}
    return headers, rest[: int(headers["Content-Length"])]


def _write(folder: str):
    schema = pa.schema([("key", pa.string()), ("page_id", pa.int64()), ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64())])

    def run(batches):
        out, name, at = None, None, 0
        for batch in pieces(batches):
            rows = {k: [] for k in schema.names}
            for page_id, url, html, refers in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "refers_to")), strict=True):
                if out is None:
                    system, path = file_system(folder)
                    system.create_dir(path, recursive=True)
                    name = f"part-{uuid.uuid4().hex}.warc.gz"
                    out = system.open_output_stream(f"{path}/{name}", compression=None)
                pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                data = pack.compress(record(page_id, url, (html or "").encode(), refers)) + pack.flush()
                out.write(data)
                for k, v in zip(schema.names, (url_key(url), page_id, name, at, len(data)), strict=True):
                    rows[k].append(v)
                at += len(data)
            yield pa.record_batch([pa.array(rows[f.name], f.type) for f in schema], schema=schema)
        if out is not None:
            out.close()

    return run


def _pack(batches):
    """Sorted captures to blocks: first, last, n, block."""
    schema = pa.schema([("first_key", pa.string()), ("last_key", pa.string()), ("n", pa.int32()), ("block", pa.binary())])
    lines: list[str] = []

    def block(part: list[str]) -> pa.RecordBatch:
        keys = [x.split("\t", 1)[0] for x in (part[0], part[-1])]
        return pa.record_batch([pa.array([keys[0]]), pa.array([keys[1]]), pa.array([len(part)], pa.int32()), pa.array([zlib.compress("\n".join(part).encode())])], schema=schema)

    for batch in batches:
        cols = (batch.column(c).to_pylist() for c in ("key", "page_id", "file", "offset", "length"))
        for key, page, file, offset, length in zip(*cols, strict=True):
            lines.append(f"{re.sub(r'[\t\n]', ' ', key)}\t{'' if page is None else page}\t{file}\t{offset}\t{length}")
        while len(lines) >= BLOCK:
            yield block(lines[:BLOCK])
            lines = lines[BLOCK:]
    if lines:
        yield block(lines)


def write_archives(pages: DataFrame) -> tuple[str, DataFrame]:
    """Writes pages (page_id, url, html); returns the archive folder and the index's block table, sorted by key over its files."""
    spark = pages.sparkSession
    pages = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")).withColumn("d", F.sha1("html"))
    light = pages.select("page_id", "d")
    latest = light.groupBy("d").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1").drop("n")
    revisits = light.join(latest, "d").where("page_id <> refers_to").dropDuplicates(["page_id", "d"])
    folder = fresh_path(spark, "warc")
    captures = stored(pages.join(revisits, ["page_id", "d"], "left").select("page_id", "url", "html", "refers_to").mapInArrow(_write(folder), "key string, page_id long, file string, offset long, length long"), "captures")
    order = ["key", "page_id", "file", "offset"]
    index = stored(captures.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_pack, "first_key string, last_key string, n int, block binary"), "capture-index")
    return folder, index


class Reader:
    """Range reads with a few open files."""

    def __init__(self, folder: str, most: int = 8):
        self.system, self.path = file_system(folder)
        self.open: OrderedDict = OrderedDict()
        self.most = most

    def read(self, name: str, offset: int, length: int) -> tuple[dict[str, str], bytes]:
        if name not in self.open:
            if len(self.open) >= self.most:
                self.open.popitem(last=False)[1].close()
            self.open[name] = self.system.open_input_file(f"{self.path}/{name}")
        self.open.move_to_end(name)
        return parse(zlib.decompress(self.open[name].read_at(length, offset), 31))


def block_lines(block: bytes) -> list[list[str]]:
    return [x.split("\t") for x in zlib.decompress(block).decode().split("\n")]


def _captures(batches):
    schema = pa.schema([("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64())])
    for batch in batches:
        for b in batch.column("block").to_pylist():
            rows = block_lines(b)
            yield pa.record_batch([pa.array([r[2] for r in rows]), pa.array([int(r[3]) for r in rows]), pa.array([int(r[4]) for r in rows])], schema=schema)


def _read(folder: str):
    schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string())])

    def number(text: str) -> int | None:
        found = _ID.fullmatch(text)
        return int(found[1]) if found else None

    def run(batches):
        reader = Reader(folder)
        for batch in pieces(batches, 2000):
            rows = []
            for file, offset, length in zip(*(batch.column(c).to_pylist() for c in ("file", "offset", "length")), strict=True):
                head, block = reader.read(file, offset, length)
                kind = head["WARC-Type"]
                if kind == "response":
                    payload = block.partition(b"\r\n\r\n")[2]
                    size, digest = len(payload), sha1_32(payload)
                    if head["WARC-Payload-Digest"] != f"sha1:{digest}":
                        raise ValueError(f"{file} at {offset}: the payload does not have its digest")
                else:
                    size, digest = int(head["X-Payload-Length"]), head["WARC-Payload-Digest"].removeprefix("sha1:")
                rows.append((number(head["WARC-Record-ID"]), size, digest, kind, number(head.get("WARC-Refers-To", "")), head.get("WARC-Target-URI")))
            yield pa.record_batch([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)

    return run


def read_archives(folder: str, index: DataFrame) -> DataFrame:
    """Every record of the archives, by the index."""
    places = index.select("block").mapInArrow(_captures, "file string, offset long, length long")
    places = places.repartitionByRange("file", "offset").sortWithinPartitions("file", "offset")
    return places.mapInArrow(_read(folder), "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string")


def look_up(folder: str, index: DataFrame, url: str) -> list[tuple[dict[str, str], bytes]]:
    """The captures of one URL: directory, bisection in the blocks, range reads."""
    key = re.sub(r"[\t\n]", " ", url_key(url))
    found = []
    for row in index.where((F.col("first_key") <= key) & (F.col("last_key") >= key)).select("block").collect():
        lines = block_lines(row["block"])
        keys = [x[0] for x in lines]
        found += lines[bisect.bisect_left(keys, key) : bisect.bisect_right(keys, key)]
    reader = Reader(folder)
    return [reader.read(file, int(offset), int(length)) for _, _, file, offset, length in found]


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder, index = write_archives(table(spark, sf_dir, "pages"))
    return read_archives(folder, index).drop("url")


def oracle() -> str:
    base32 = "array_to_string(list_transform(range(0, 4), lambda k: array_to_string(list_transform(range(0, 8), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(h, 10 * k + 1, 10) AS BIGINT) >> CAST(35 - 5 * i AS BIGINT)) & 31 AS BIGINT) + 1, 1)), '')), '')"
    return f"""
    WITH p AS (SELECT page_id, coalesce(html, '') AS t, sha1(coalesce(html, '')) AS h FROM pages),
    q AS (SELECT page_id, strlen(t) AS payload_bytes, {base32} AS payload_digest, max(page_id) OVER (PARTITION BY h) AS m FROM p)
    SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = m THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = m THEN NULL ELSE m END AS refers_to FROM q
    """
