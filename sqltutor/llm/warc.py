"""WARC archives: an index of record ranges first, then coalesced byte-range reads.

Writing tasks append one gzip member per record and emit an index row (file, offset, length, URL, digest). Reading
sorts the wanted index rows by file and offset, joins ranges that lie close together into one read, and parses records.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, parts_for, text_of
from .files import NewFile, open_fs

MIN_REVISIT, ROLL, GAP, SPAN, TASK = 100, 256 << 20, 16 << 10, 8 << 20, 64 << 20
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
INDEX = "page_id long, url string, digest string, file string, offset long, length long"
READ = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def _urn(page_id: int | None, salt: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{salt}')}>"


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record. A revisit keeps no payload; it names the record that has it and the payload's length."""
    kind = "response" if refers_to is None else "revisit"
    target = "".join("%0D" if c == "\r" else "%0A" if c == "\n" else c for c in url or "")
    head = [("WARC-Type", kind), ("WARC-Record-ID", _urn(page_id, digest)), ("WARC-Date", DATE), ("WARC-Target-URI", target),
            ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Payload-Length", len(payload))]
    if url is None:
        head = [x for x in head if x[0] != "WARC-Target-URI"]
    if page_id is not None:
        head.append(("X-Page-Id", page_id))
    if refers_to is not None:
        head += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", _urn(refers_to, digest)), ("X-Refers-To-Page", refers_to)]
        payload = b""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    head += [("Content-Type", "application/http; msgtype=response"), ("Content-Length", len(http) + len(payload))]
    return "".join(["WARC/1.1\r\n", *(f"{k}: {v}\r\n" for k, v in head), "\r\n"]).encode() + http + payload + b"\r\n\r\n"


def parse(data: bytes) -> dict:
    """Record bytes -> header fields and payload; lengths and the payload's digest are verified."""
    end = data.index(b"\r\n\r\n")
    lines = data[:end].decode().split("\r\n")
    if not lines[0].startswith("WARC/1."):
        raise ValueError("not a WARC record")
    head = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines[1:])
    block = data[end + 4 : end + 4 + int(head["Content-Length"])]
    if data[end + 4 + len(block) :] != b"\r\n\r\n":
        raise ValueError("record length and Content-Length disagree")
    payload = block[block.index(b"\r\n\r\n") + 4 :]
    digest = head["WARC-Payload-Digest"].removeprefix("sha256:")
    if head["WARC-Type"] == "response" and (hashlib.sha256(payload).hexdigest() != digest or len(payload) != int(head["X-Payload-Length"])):
        raise ValueError("payload and digest disagree")
    number = lambda k: int(head[k]) if k in head else None
    return {"page_id": number("X-Page-Id"), "url": head.get("WARC-Target-URI"), "payload_bytes": number("X-Payload-Length"),
            "payload_digest": digest, "record_type": head["WARC-Type"], "refers_to": number("X-Refers-To-Page"), "payload": payload}


def _member(data: bytes) -> bytes:
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def _writer(root: str):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = None
        for b in batches:
            rows = []
            for page, url, html, refers in zip(*(c.to_pylist() for c in b.columns), strict=True):
                payload = html.encode()
                digest = hashlib.sha256(payload).hexdigest()
                if out is None or out.size >= ROLL:
                    if out:
                        out.close()
                    out = NewFile(root, ".warc.gz")
                data = _member(record(page, url, payload, digest, refers))
                rows.append((page, url, digest, out.name, out.write(data), len(data)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [f.split()[0] for f in INDEX.split(", ")])
        if out:
            out.close()

    return write


def _reader(root: str, with_payload: bool):
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
    names = [f.split()[0] for f in READ.split(", ")]

    def runs(rows):
        """Rows in order of file and offset -> (file, start, end, rows) with gaps up to GAP closed and spans up to SPAN."""
        now = None
        for file, offset, length in rows:
            if now and now[0] == file and 0 <= offset - now[2] <= GAP and offset + length - now[1] <= SPAN:
                now[2] = max(now[2], offset + length)
                now[3].append((offset, length))
            else:
                if now:
                    yield now
                now = [file, offset, offset + length, [(offset, length)]]
        if now:
            yield now

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, base = open_fs(root)
        rows = (x for b in batches for x in zip(*(c.to_pylist() for c in b.columns), strict=True))
        name, handle = None, None
        for file, start, end, parts in runs(rows):
            if file != name:
                if handle:
                    handle.close()
                name, handle = file, system.open_input_file(f"{base}/{file}")
            data = handle.read_at(end - start, start)
            found = [parse(zlib.decompress(data[o - start : o - start + n], 31)) for o, n in parts]
            if not with_payload:
                for x in found:
                    x["payload"] = None
            yield pa.RecordBatch.from_arrays([pa.array([x[c] for x in found], k) for c, k in zip(names, kinds, strict=True)], names)
        if handle:
            handle.close()

    return read


def revisits(pages: DataFrame) -> DataFrame:
    """``(page_id, mark, refers_to)`` of the pages whose payload an earlier page (smaller id) has: the only rows that
    are not plain responses. Payloads are digested once, here, and copies counted by digest with partial sums; no group
    meets in one task."""
    hashed = Scratch(pages.sparkSession, "digests").save(
        pages.select("page_id", _mark().alias("mark"), F.sha2(text_of("html").cast("binary"), 256).alias("digest"),
                     F.octet_length(text_of("html")).alias("n")), "digests")
    shared = (hashed.where(F.col("n") >= MIN_REVISIT).groupBy("digest")
              .agg(F.min("page_id").alias("refers_to"), F.count("*").alias("copies")).where("copies > 1").drop("copies"))
    return (hashed.where(F.col("n") >= MIN_REVISIT).join(shared, "digest")
            .where(F.col("page_id") != F.col("refers_to")).select("page_id", "mark", "refers_to").distinct())


def _mark() -> Column:
    """Tells payloads under one id apart, at less cost than a digest."""
    return F.xxhash64(text_of("html"))


def write(spark: SparkSession, pages: DataFrame) -> tuple[DataFrame, str]:
    """Archives all pages; returns the index table and the folder of the archives."""
    scratch = Scratch(spark, "warc")
    again = scratch.save(revisits(pages), "revisits")
    rows = pages.select("page_id", "url", text_of("html").alias("html"), _mark().alias("mark"))
    rows = rows.join(again, ["page_id", "mark"], "left").select("page_id", "url", "html", "refers_to")
    return scratch.save(rows.mapInArrow(_writer(scratch.path("archive")), INDEX), "index"), scratch.path("archive")


def read(index: DataFrame, root: str, with_payload: bool = True) -> DataFrame:
    """Selected index rows -> records, in few large reads. Filter ``index`` by URL or digest first to read less.

    The number of tasks follows the selected bytes, ``TASK`` a task; the index itself is too small to tell."""
    size = index.agg(F.coalesce(F.sum("length"), F.lit(0))).first()[0]
    parts = parts_for(index.sparkSession, size, TASK)
    ranges = index.select("file", "offset", "length").repartitionByRange(parts, "file", "offset").sortWithinPartitions("file", "offset")
    return ranges.mapInArrow(_reader(root, with_payload), READ)


def archive_digest(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """One row per row of ``pages`` as read back. Null html: an empty payload; null URL: no target header; a page
    without an id is a response (it cannot be smallest, and copies of it refer to the smallest id there is). Rows that
    repeat id and payload are responses both. Empty table: no archives, no rows."""
    index, root = write(spark, pages)
    return read(index, root, with_payload=False).drop("payload", "url")
