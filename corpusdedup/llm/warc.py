"""WARC archives: segmented records with chunked payloads, written and read back.

Writing: a record for each page, its payload the UTF-8 bytes of the html framed as a
chunked HTTP response. Of pages with equal payloads of at least ``revisit_from`` bytes
the one with the smallest page_id is a response and the others are revisit records
without payload that name it; below that size all are responses. A record whose block
exceeds ``segment_bytes`` is cut into a first segment and continuation records, which
may lie in other files.

Reading: whole records are decoded where they are found. Segments are grouped by the
identifier of their origin, ordered by number and joined; the numbers must run from 1
without a gap and the last segment's total length must be the sum. Then the chunked
framing is decoded. What fails is returned with ``error`` set instead of a payload.

A null html is an empty payload, a null url an empty URI. Rows with the same page_id
and payload as the smallest are responses too; a null page_id never is the origin of a
revisit unless all are null, when all are responses. Other columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid
from collections.abc import Iterator
from typing import BinaryIO

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import fresh_path, stage
from .files import make_folder, small, write_whole

SEGMENT_BYTES, CHUNK_BYTES, FILE_BYTES = 4_096, 2_048, 8_000_000
DATE = "2000-01-01T00:00:00Z"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n"
IDENTICAL = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def digest_of(payload: bytes) -> str:
    """Bare base32 SHA-1, upper case."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def frame(payload: bytes, chunk: int = CHUNK_BYTES) -> bytes:
    """Chunked transfer framing."""
    out = []
    for k in range(0, len(payload), chunk):
        part = payload[k : k + chunk]
        out += [b"%x\r\n" % len(part), part, b"\r\n"]
    return b"".join([*out, b"0\r\n\r\n"])


def unframe(body: bytes) -> bytes:
    """Decode chunked transfer framing; chunk extensions and trailers are skipped."""
    out, at = [], 0
    while True:
        end = body.index(b"\r\n", at)
        n = int(body[at:end].split(b";")[0], 16)
        at = end + 2
        if n == 0:
            return b"".join(out)
        if body[at + n : at + n + 2] != b"\r\n":
            raise ValueError("a chunk does not end where its size says")
        out.append(body[at : at + n])
        at += n + 2


def record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def records_of(archive: BinaryIO) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields in lower case, block) of each record of an uncompressed archive, one record in memory at a time."""
    while line := archive.readline():
        if not line.startswith(b"WARC/"):
            raise ValueError("no record begins where one should")
        fields = {}
        while (line := archive.readline()) not in (b"\r\n", b""):
            k, _, v = line.decode("utf-8").partition(":")
            fields[k.strip().lower()] = v.strip()
        n = int(fields["content-length"])
        block = archive.read(n)
        if len(block) != n or archive.read(4) != b"\r\n\r\n":
            raise ValueError("a record does not end where its length says")
        yield fields, block


def urn(name: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, name)}>"


def uri(url: str | None) -> str:
    """A URL without white space: a line break would end the header."""
    return "".join((url or "").split())


def page_records(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, name: str, segment: int, chunk: int, target: str | None = None, target_url: str | None = None) -> Iterator[bytes]:
    """The record of a page, or its segments.

    A revisit names its response by the standard's fields (record id where there is one
    such record, URI and date) and by page; the page and the payload's length are fields of
    their own, for the standard has none.
    """
    identifier = urn(name)
    fields = [("WARC-Record-ID", identifier), ("WARC-Date", DATE), ("WARC-Target-URI", uri(url)), ("WARC-Payload-Digest", "sha1:" + digest_of(payload)), ("WARC-Page-ID", "" if page_id is None else str(page_id))]
    if refers_to is not None:
        yield record([("WARC-Type", "revisit"), *fields, ("WARC-Profile", IDENTICAL), *([("WARC-Refers-To", urn(target))] if target else []), ("WARC-Refers-To-Target-URI", uri(target_url)), ("WARC-Refers-To-Date", DATE), ("WARC-Refers-To-Page", str(refers_to)), ("WARC-Payload-Length", str(len(payload))), ("Content-Type", "application/http;msgtype=response")], HTTP)
        return
    block = HTTP + frame(payload, chunk)
    fields += [("Content-Type", "application/http;msgtype=response")]
    if len(block) <= segment:
        yield record([("WARC-Type", "response"), *fields], block)
        return
    last = -(-len(block) // segment)
    for k in range(last):
        part = block[k * segment : (k + 1) * segment]
        number = ("WARC-Segment-Number", str(k + 1))
        if k == 0:
            yield record([("WARC-Type", "response"), *fields, number], part)
        else:
            own = f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{name}#{k}')}>"
            yield record([("WARC-Type", "continuation"), ("WARC-Record-ID", own), ("WARC-Segment-Origin-ID", identifier), number, *([("WARC-Segment-Total-Length", str(len(block)))] if k == last - 1 else [])], part)


def write_archives(pages: DataFrame, folder: str | None = None, revisit_from: int = 0, segment_bytes: int = SEGMENT_BYTES, chunk_bytes: int = CHUNK_BYTES, file_bytes: int = FILE_BYTES) -> tuple[str, DataFrame]:
    """Write (page_id, url, html) as gzipped archives; returns their folder and the staged list of files."""
    folder = folder or fresh_path(pages.sparkSession, "warc")
    make_folder(pages.sparkSession, folder)
    html = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    # the digest decides which pages are equal before any html moves
    told = pages.select(F.col("page_id").cast("long").alias("page_id"), F.sha1(html).alias("sha"), F.length(html).alias("n"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("url"))
    firsts = told.where((F.col("n") >= revisit_from) & F.col("page_id").isNotNull()).groupBy("sha", "page_id").agg(F.min("url").alias("url"), F.count("*").alias("rows"))
    copies = told.where(F.col("n") >= revisit_from).groupBy("sha").agg(F.count("*").alias("copies")).where("copies > 1")
    firsts = firsts.join(copies, "sha").groupBy("sha").agg(F.min(F.struct("page_id", "url", "rows")).alias("f"))
    firsts = stage(firsts.select("sha", F.col("f.page_id").alias("first"), F.col("f.url").alias("first_url"), (F.col("f.rows") == 1).alias("sole")), "warc-firsts")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("payload"), F.sha1(html).alias("sha")).join(small(firsts), "sha", "left")
    # a response that is alone has a name which its revisits can make from the payload
    rows = rows.select("page_id", "url", "payload", F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to"), F.when(F.col("sole"), F.concat(F.lit(f"{folder}/response/"), "sha")).alias("target"), "first_url")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        salt = f"{folder}/{task.partitionId()}"
        count = number = size = 0
        parts: list[bytes] = []

        def close() -> pa.RecordBatch:
            name = f"pages-{task.partitionId():06d}-{number:06d}-{task.taskAttemptId()}.warc.gz"
            write_whole(folder, name, b"".join(parts))
            return pa.RecordBatch.from_arrays([pa.array([name], pa.string()), pa.array([size], pa.int64())], names=["file", "bytes"])

        for batch in batches:
            for page_id, url, payload, refers_to, target, target_url in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
                name = target if target and refers_to is None else f"{salt}/{count}"
                for data in page_records(page_id, url, payload, refers_to, name, segment_bytes, chunk_bytes, target, target_url):
                    if parts and size >= file_bytes:
                        yield close()
                        number, size, parts = number + 1, 0, []
                    parts.append(gzip.compress(data, 1, mtime=0))
                    size += len(parts[-1])
                count += 1
        if parts:
            yield close()

    return folder, stage(rows.mapInArrow(run, "file string, bytes long"), "warc-files")


SEGMENT = "origin string, number int, total long, digest string, block binary"
PAGES = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary, error string"


def _payload(block: bytes) -> bytes:
    head, _, body = block.partition(b"\r\n\r\n")
    return unframe(body) if b"transfer-encoding: chunked" in head.lower() else body


def _row(first: dict, block: bytes, error: str | None) -> list:
    """A page's output row from its first record's fields and the joined block."""
    payload = None
    if error is None and first["record_type"] == "revisit":
        return [first["page_id"], first["url"], first["revisit_bytes"], first["digest"], "revisit", first["refers_to"], None, None]
    if error is None:
        try:
            payload = _payload(block)
        except ValueError as e:
            error = f"framing: {e}"
        else:
            if digest_of(payload) != first["digest"]:
                error, payload = "payload digest differs", None
    return [first["page_id"], first["url"], None if payload is None else len(payload), None if payload is None else digest_of(payload), first["record_type"], None, payload, error]


def _table(rows: list[list]) -> pa.Table:
    kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary(), pa.string())
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(kinds)
    return pa.table({n: pa.array(c, k) for n, c, k in zip(PAGES.replace(",", "").split()[::2], cols, kinds, strict=True)})


def join_segments(rows: list[dict]) -> tuple[dict | None, bytes, str | None]:
    """Order, check and join the segments of one origin: (first record, block, error)."""
    rows = sorted(rows, key=lambda r: r["number"])
    first = rows[0] if rows[0]["number"] == 1 else None
    if first is None or [r["number"] for r in rows] != list(range(1, len(rows) + 1)):
        return first, b"", "segments are missing or repeated"
    block = b"".join(r["block"] for r in rows)
    if rows[-1]["total"] != len(block):
        return first, b"", "total length differs"
    return first, block, None


def read_archives(spark: SparkSession, folder: str, files: DataFrame | None = None, pattern: str = "*.warc.gz", payloads: bool = True) -> DataFrame:
    """Pages of all archives of a folder (or of the listed files), with errors and, if wanted, payloads."""
    names = PAGES.replace(",", "").split()[::2]
    page_schema = _table([]).schema
    schema = pa.schema([*page_schema, ("origin", pa.string()), ("number", pa.int32()), ("total", pa.int64()), ("digest", pa.string()), ("block", pa.binary())])
    number = lambda x: int(x) if x else None

    def finished(row: list) -> dict:
        return dict(zip(names, row, strict=True)) | ({} if payloads else {"payload": None})

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0):
                out: list[dict] = []
                size = 0
                for f, block in records_of(io.BufferedReader(gzip.GzipFile(fileobj=io.BytesIO(data.as_buffer())), 1 << 20)):
                    kind = f["warc-type"]
                    if kind not in ("response", "revisit", "continuation"):
                        continue
                    known = {"page_id": number(f.get("warc-page-id")), "url": f.get("warc-target-uri"), "record_type": kind, "digest": f.get("warc-payload-digest", "").removeprefix("sha1:"), "refers_to": number(f.get("warc-refers-to-page")), "revisit_bytes": number(f.get("warc-payload-length"))}
                    if "warc-segment-number" in f:
                        segment = {"origin": f.get("warc-segment-origin-id", f["warc-record-id"]), "number": number(f["warc-segment-number"]), "total": number(f.get("warc-segment-total-length")), "block": block}
                        out.append({k: known[k] for k in ("page_id", "url", "record_type", "digest")} | segment)
                        size += len(block)
                    else:
                        out.append(finished(_row(known, block, None)))
                        size += len(block) * payloads + 200
                    if size > 4_000_000:
                        yield pa.RecordBatch.from_pylist(out, schema=schema)
                        out, size = [], 0
                yield pa.RecordBatch.from_pylist(out, schema=schema)

    def joined(table: pa.Table) -> pa.Table:
        first, block, error = join_segments(table.to_pylist())
        first = first or {"page_id": None, "url": None, "record_type": "continuation", "digest": None}
        return pa.Table.from_pylist([finished(_row(first, block, error))], schema=page_schema)

    raw = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(folder)
    if files is not None:
        raw = raw.withColumn("file", F.element_at(F.split("path", "/"), -1)).join(small(files.select("file")), "file", "left_semi")
    found = stage(raw.select("content").mapInArrow(parse, f"{PAGES}, {SEGMENT}"), "warc-records")
    return found.where("number is null").select(*names).unionByName(found.where("number is not null").groupBy("origin").applyInArrow(joined, PAGES))
