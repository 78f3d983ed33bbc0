"""WARC archives written with an index first, and read back by coalesced byte ranges of selected records.

A record of a payload of at least ``MIN_SHARED`` bytes that an earlier page has too (smaller page_id) is a ``revisit`` without
the payload: it names the response, the digest and the length of the full payload. Each record is a gzip member of its own,
so it can be read alone from its offset and length.
"""

from __future__ import annotations

import hashlib
import itertools
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, scratch_path

MIN_SHARED = 100
ARCHIVE_BYTES = 64 << 20
GAP, READ = 64 << 10, 8 << 20  # ranges with smaller gaps are read at once, up to so many bytes
INDEX = "archive string, offset long, length long, page_id long, url string, digest string, record_type string, refers_to long"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"


def plan_records(pages: DataFrame, min_shared: int = MIN_SHARED) -> DataFrame:
    """page_id, url, payload, digest, record_type, refers_to.

    The smallest page_id of each shared digest is found by a partial aggregation and stored, so that the join back is between two
    plain scans and a digest of a third of all rows is split by adaptive execution. A null html is an empty payload.
    Rows that share both the payload and the smallest page_id are all responses.
    """
    payload = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").alias("url"), payload.alias("payload"), F.sha2(payload.cast("binary"), 256).alias("digest"))
    long_enough = rows.filter(F.octet_length("payload") >= min_shared)
    shared = long_enough.groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    shared = materialize(shared.select(F.col("digest").alias("_d"), "first"), "warc-shared")
    again = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return rows.join(shared, rows.digest == shared._d, "left").select(
        "page_id", "url", F.when(again, F.lit("")).otherwise(F.col("payload")).alias("payload"), F.octet_length("payload").cast("long").alias("size"), "digest",
        F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("first")).alias("refers_to"),
    )


def _id(page: int | None, digest: str) -> str:
    return f"<urn:prefgraph:page:{'none-' + digest[:32] if page is None else page}>"


def _uri(url: str | None) -> str:
    return "urn:prefgraph:no-url" if url is None else re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)


def build_record(page, url, payload: bytes, size: int, digest: str, kind: str, refers, date: str) -> bytes:
    block = _HTTP % size + payload if kind == "response" else _HTTP % size
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {_id(page, digest)}", f"WARC-Date: {date}", f"WARC-Target-URI: {_uri(url)}",
        f"WARC-Payload-Digest: sha256:{digest}", "Content-Type: application/http; msgtype=response",
    ]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_id(refers, digest)}"]
    return "\r\n".join([*head, f"Content-Length: {len(block)}", "", ""]).encode() + block + b"\r\n\r\n"


def parse_record(raw: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = lambda b: dict(x.split(": ", 1) for x in b.decode().split("\r\n")[1:])
    warc = fields(head)
    http, _, payload = rest[: int(warc["Content-Length"])].partition(b"\r\n\r\n")
    return warc, fields(http), payload


def _member(raw: bytes) -> bytes:
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def write_archives(records: DataFrame, folder: str, date: str = "2000-01-01T00:00:00Z", archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Write records (as of plan_records) below folder and return their stored index (INDEX).

    A task writes archives under names of its own attempt and the index rows it returns name them: what a lost or repeated
    attempt leaves behind is in no index. Memory of a task is one batch and one record.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = pafs.FileSystem.from_uri(folder)
        fs.create_dir(base, recursive=True)
        out, name, at = None, "", 0
        for batch in batches:
            index = []
            for page, url, payload, size, digest, kind, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if out is None:
                    name, at = f"{uuid.uuid4().hex}.warc.gz", 0
                    out = fs.open_output_stream(f"{base}/{name}", compression=None)
                raw = _member(build_record(page, url, payload.encode(), size, digest, kind, refers, date))
                out.write(raw)
                index.append((name, at, len(raw), page, url, digest, kind, refers))
                at += len(raw)
                if at >= archive_bytes:
                    out.close()
                    out = None
            yield _batch(index, INDEX)
        if out is not None:
            out.close()

    return materialize(records.select("page_id", "url", "payload", "size", "digest", "record_type", "refers_to").mapInArrow(write, INDEX), "warc-index")


_TYPES = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [f.split(" ") for f in schema.split(", ")]
    columns = zip(*rows, strict=True) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, _TYPES[t]) for c, (_, t) in zip(columns, fields, strict=True)], [n for n, _ in fields])


def coalesce_ranges(spans: list[tuple[int, int]], gap: int = GAP, most: int = READ) -> Iterator[tuple[int, int, list[int]]]:
    """(start, end, positions in spans) of the reads for sorted (offset, length) pairs."""
    start = end = 0
    inside: list[int] = []
    for i, (offset, length) in enumerate(spans):
        if inside and (offset - end > gap or offset + length - start > most):
            yield start, end, inside
            inside = []
        if not inside:
            start = end = offset
        end = max(end, offset + length)
        inside.append(i)
    if inside:
        yield start, end, inside


RECORDS = "page_id long, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def read_records(selected: DataFrame, folder: str, keep_payload: bool = True) -> DataFrame:
    """Read the records of the selected index rows: sorted by archive and offset, neighbours in one read.

    payload_bytes and payload_digest are of the full payload: of the bytes read for a response, as recorded for a revisit (whose
    payload is null). A record whose bytes do not fit its header or index fails the task.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = pafs.FileSystem.from_uri(folder)
        for batch in batches:
            rows = list(zip(*(c.to_pylist() for c in batch.columns), strict=True))
            for archive, part in itertools.groupby(rows, key=lambda r: r[0]):
                part = list(part)
                with fs.open_input_file(f"{base}/{archive}") as src:
                    for start, end, inside in coalesce_ranges([r[1:3] for r in part]):
                        data, out = memoryview(src.read_at(end - start, start)), []
                        for _, offset, length, page, digest, kind, refers in (part[i] for i in inside):
                            warc, http, payload = parse_record(zlib.decompress(data[offset - start : offset - start + length], 31))
                            found = hashlib.sha256(payload).hexdigest() if warc["WARC-Type"] == "response" else warc["WARC-Payload-Digest"].removeprefix("sha256:")
                            if (found, warc["WARC-Type"], warc["WARC-Record-ID"]) != (digest, kind, _id(page, digest)):
                                raise ValueError(f"{archive} at {offset}: the record does not fit the index")
                            size = len(payload) if kind == "response" else int(http["Content-Length"])
                            out.append((page, kind, refers, size, found, payload if keep_payload and kind == "response" else None))
                        yield _batch(out, RECORDS)

    order = ["archive", "offset"]
    ranged = selected.select("archive", "offset", "length", "page_id", "digest", "record_type", "refers_to").repartitionByRange(*order).sortWithinPartitions(*order)
    return ranged.mapInArrow(read, RECORDS)


def archive_pages(pages: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every page, from the archives read back.

    Pages with a null id, url or html are archived like others; an empty table writes nothing and gives no rows.
    """
    folder = scratch_path(pages.sparkSession, "warc")
    index = write_archives(plan_records(pages), folder)
    return read_records(index, folder, keep_payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes, sha256(h) AS payload_digest FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS f FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= {MIN_SHARED} AND f <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= {MIN_SHARED} AND f <> page_id THEN f END AS refers_to FROM f
"""
