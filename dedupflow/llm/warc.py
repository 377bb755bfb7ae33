"""WARC archives: an index of offset, length, URL and digest per record is written with them; reads go by the index."""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, scratch, written

INDEX = "file string, offset long, length long, url string, payload_digest string, payload_bytes long, page_id long, record_type string, refers_to long"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def record(page_id, url: str, payload: bytes, digest: str, refers_to, date: str) -> bytes:
    """One WARC record, compressed as a gzip member of its own."""
    block = _HTTP if refers_to is not None else _HTTP + payload
    lines = [
        "WARC/1.1", f"WARC-Type: {'revisit' if refers_to is not None else 'response'}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Target-URI: {' '.join(url.split())}",
        f"WARC-Date: {date}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}",
        *([f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {_PROFILE}"] if refers_to is not None else []),
        "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}",
    ]
    squeeze = zlib.compressobj(1, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + squeeze.flush()


def parse(member: bytes) -> dict:
    """Headers (lower-case names) and payload of one compressed record."""
    raw = zlib.decompress(member, 31)
    head, _, rest = raw.partition(b"\r\n\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode().split("\r\n")[1:])}
    block = rest[: int(headers["content-length"])]
    return {"headers": headers, "payload": block.partition(b"\r\n\r\n")[2]}


def write(pages: DataFrame, folder: str, min_bytes: int = 0, date: str = "2024-01-01T00:00:00Z", roll: int = 64 << 20) -> DataFrame:
    """Writes one record per row of (page_id, url, html) to archives in ``folder``; returns the index, itself written.

    Of records with equal payloads of at least ``min_bytes`` the one with the smallest page_id is a response and the
    others revisit it. A null html is an empty payload, a null url an empty one; rows that repeat the smallest page_id
    are responses. Rows without page_id are never referred to and never revisit. Archives roll at ``roll`` bytes.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce("url", F.lit("")).alias("url"), F.coalesce(F.encode("html", "UTF-8"), F.lit(b"")).alias("payload"))
    keys = rows.where(F.col("page_id").isNotNull() & (F.octet_length("payload") >= min_bytes)).select("page_id", F.unhex(F.sha1("payload")).alias("digest"))
    again = written(keys.join(keys.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.count(F.lit(1)).alias("n")).where("n > 1"), "digest").where("page_id > refers_to").select("page_id", "refers_to", "digest").distinct(), "revisits")
    n = again.count()
    side = again.select(F.col("page_id").alias("again_id"), "refers_to", F.col("digest").alias("again_digest"))
    side = F.broadcast(side) if n <= BROADCAST_ROWS else side
    joined = rows.withColumn("digest", F.unhex(F.sha1("payload"))).join(side, (F.col("page_id") == F.col("again_id")) & (F.col("digest") == F.col("again_digest")), "left").select("page_id", "url", "payload", "digest", "refers_to")

    def archive(batches):
        files, base = _filesystem(folder)
        out, name, at = None, "", 0
        for b in batches:
            index = []
            for page, url, payload, digest, refers in zip(*(c.to_pylist() for c in b.columns)):
                if out is None or at >= roll:
                    if out is not None:
                        out.close()
                    name, at = f"{uuid.uuid4().hex}.warc.gz", 0  # a retried task writes new files; the index names only those of the attempt that counted
                    out = files.open_output_stream(f"{base}/{name}", compression=None)
                b32 = base64.b32encode(digest).decode()
                member = record(page, url, payload, b32, refers, date)
                out.write(member)
                index.append((f"{folder}/{name}", at, len(member), url, b32, len(payload), page, "response" if refers is None else "revisit", refers))
                at += len(member)
            kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64())
            cols = list(zip(*index)) or [()] * 9
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], [x.split()[0] for x in INDEX.split(", ")])
        if out is not None:
            out.close()

    return written(joined.mapInArrow(archive, INDEX), "warc-index")


def read(index: DataFrame, gap: int = 1 << 16, most: int = 8 << 20, task_bytes: int = 64 << 20) -> DataFrame:
    """Reads the records that ``index`` selects (any subset of its rows).

    The records are dealt in order of file and offset to as many tasks as their bytes need at ``task_bytes`` each, and at
    least one per core, so that a task reads runs of few files. Within it ranges closer than ``gap`` bytes are read at once, ``most`` bytes at
    most together (a longer record alone). Gives what the archives say: page_id, url, payload, digest recomputed where
    there is a payload, type and reference. A record whose payload does not have its digest raises an error.
    """
    total = index.agg(F.sum("length")).first()[0] or 0
    tasks = max(-(-total // task_bytes), index.sparkSession.sparkContext.defaultParallelism)
    wanted = index.select("file", "offset", "length").repartitionByRange(int(tasks), "file", "offset").sortWithinPartitions("file", "offset")

    def fetch(batches):
        for b in batches:
            rows = list(zip(*(c.to_pylist() for c in b.columns)))
            got, i = [], 0
            while i < len(rows):
                file, start, length = rows[i]
                end, j = start + length, i + 1
                while j < len(rows) and rows[j][0] == file and 0 <= rows[j][1] - end <= gap and rows[j][1] + rows[j][2] - start <= most:
                    end, j = rows[j][1] + rows[j][2], j + 1
                files, path = _filesystem(file)
                with files.open_input_file(path) as f:
                    data = f.read_at(end - start, start)
                for _, offset, size in rows[i:j]:
                    r = parse(data[offset - start : offset - start + size])
                    h, payload = r["headers"], r["payload"]
                    kind, digest = h["warc-type"], h["warc-payload-digest"].removeprefix("sha1:")
                    if kind == "response" and base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                        raise ValueError(f"digest differs at {file}:{offset}")
                    number = lambda x: None if x in (None, "<urn:page:None>") else int(x.removeprefix("<urn:page:").rstrip(">"))
                    got.append((number(h["warc-record-id"]), h["warc-target-uri"], payload if kind == "response" else None, int(h["x-payload-length"]), digest, kind, number(h.get("warc-refers-to"))))
                i = j
                if sum(len(x[2] or b"") for x in got) >= most:
                    yield _records(got)
                    got = []
            if got:
                yield _records(got)

    return wanted.mapInArrow(fetch, "page_id long, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to long")


def _records(got: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.string(), pa.binary(), pa.int64(), pa.string(), pa.string(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*got), kinds)], ["page_id", "url", "payload", "payload_bytes", "payload_digest", "record_type", "refers_to"])


def round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Writes archives of all rows to the shared folder and reads every record back."""
    folder = scratch(pages.sparkSession, "warc")
    return read(write(pages, folder, min_bytes)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
