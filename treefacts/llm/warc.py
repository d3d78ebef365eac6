"""WARC archives of pages: revisit records for equal payloads, segmented records, chunked transfer framing.

Writing: each page is one record, its HTTP block framed in chunks. A block of over segment_bytes goes to a first
segment and continuation records. Records go out as raw bytes through Spark's text sink, whose line feed is the last byte of each
record, so files are plain WARC on any file system and a lost executor's task is run again without leaving traces.

Reading: records are cut out by their lengths. Segments are grouped by the identifier of their origin, ordered by
number and held against the total length; then the HTTP block is split and its chunks are joined. A record that doesn't
add up is an error.

Null or empty html: an empty payload. A null page id never takes part in revisits; its records have the id `null`.
Rows with equal id and equal payload: all are responses (or revisits of a smaller id), and share a record id.
"""

from __future__ import annotations

import gzip
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefacts.llm import common

CRLF = b"\r\n"
LEAST_BYTES = 100  #: smaller payloads are never revisits
SEGMENT_BYTES = 48 * 1024
CHUNK_BYTES = 8 * 1024
FILE_BYTES = 8_000_000  #: of payloads that a file should hold, until there are MANY_FILES
MANY_FILES, MOST_BYTES = 4_096, 256_000_000  #: beyond so many files they grow up to MOST_BYTES each
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def record(kind: str, record_id: str, headers: list[tuple[str, object]], block: bytes) -> bytes:
    """A record without the last of its two empty lines' line feeds."""
    lines = [("WARC-Type", kind), ("WARC-Record-ID", f"<{record_id}>"), ("WARC-Date", DATE), *headers, ("Content-Length", len(block))]
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in lines).encode() + CRLF + block + b"\r\n\r"


def chunked(payload: bytes, size: int) -> bytes:
    parts = [payload[i : i + size] for i in range(0, len(payload), size)]
    return b"".join(b"%x\r\n%b\r\n" % (len(p), p) for p in parts) + b"0\r\n\r\n"


def unchunked(body: bytes) -> bytes:
    out, at = [], 0
    while True:
        end = body.index(CRLF, at)
        size = int(body[at:end].split(b";")[0], 16)
        at = end + 2
        if not size:
            break
        if len(body) < at + size + 2 or body[at + size : at + size + 2] != CRLF:
            raise ValueError("a chunk is cut")
        out.append(body[at : at + size])
        at += size + 2
    return b"".join(out)


def page_records(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, segment_bytes: int, chunk_bytes: int) -> Iterator[bytes]:
    digest = hashlib.sha256(payload).hexdigest()
    name = lambda i: f"urn:page:{'null' if i is None else i}:{digest[:16]}"
    common_ = [("WARC-Payload-Digest", f"sha256:{digest}")]
    if url:
        common_.insert(0, ("WARC-Target-URI", "".join(url.split())))
    if refers_to is not None:
        block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
        yield record("revisit", name(page_id), [*common_, ("WARC-Profile", PROFILE), ("WARC-Refers-To", f"<{name(refers_to)}>"), ("Content-Type", "application/http; msgtype=response")], block)
        return
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload, chunk_bytes)
    kind = ("Content-Type", "application/http; msgtype=response")
    if len(block) <= segment_bytes:
        yield record("response", name(page_id), [*common_, kind], block)
        return
    parts = [block[i : i + segment_bytes] for i in range(0, len(block), segment_bytes)]
    yield record("response", name(page_id), [*common_, ("WARC-Segment-Number", 1), kind], parts[0])
    for i, part in enumerate(parts[1:], 2):
        last = [("WARC-Segment-Total-Length", len(block))] if i == len(parts) else []
        yield record("continuation", f"{name(page_id)}:{i}", [("WARC-Segment-Origin-ID", f"<{name(page_id)}>"), ("WARC-Segment-Number", i), *last], part)


def write(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", segment_bytes: int = SEGMENT_BYTES, chunk_bytes: int = CHUNK_BYTES, compress: bool = True) -> None:
    """Writes the archives of pages (each file compressed as a whole, if compress is set); of equal payloads the one with the smallest id is a response, others revisit it."""
    html = F.coalesce(F.col(html_col), F.lit(""))
    source = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).alias("url"), F.encode(html, "UTF-8").alias("payload"))
    meta = source.select("id", F.sha2("payload", 256).alias("digest"), F.length("payload").alias("bytes"))
    large = meta.where(F.col("id").isNotNull() & (F.col("bytes") >= LEAST_BYTES))
    firsts = large.groupBy("digest").agg(F.min("id").alias("first"), F.max("id").alias("last")).where("first < last").drop("last")
    revisits = large.join(firsts, "digest").where("id > first").groupBy("id", "digest").agg(F.min("first").alias("first"))
    total = meta.agg(F.sum("bytes")).first()[0] or 0
    small = -(-total // FILE_BYTES)
    n_files = max(1, small if small <= MANY_FILES else max(MANY_FILES, -(-total // MOST_BYTES)))
    # one shuffle of the payloads: both sides are dealt to the files by the join's keys
    by = lambda df: df.repartition(n_files, "id", "digest")
    marked = by(source.withColumn("digest", F.sha2("payload", 256))).join(by(revisits), ["id", "digest"], "left").select("id", "url", "payload", "first")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([pa.array([record("warcinfo", "urn:treefacts:archive", [("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n")], pa.binary())], names=["value"])
        for batch in batches:
            for i in range(0, batch.num_rows, 200):
                part = batch.slice(i, 200).to_pydict()
                out = [r for page in zip(part["id"], part["url"], part["payload"], part["first"], strict=True) for r in page_records(*page, segment_bytes, chunk_bytes)]
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["value"])

    marked.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value")).write.option("compression", "gzip" if compress else "none").text(folder)


def records(content: bytes) -> Iterator[tuple[dict[str, str], memoryview]]:
    """Headers (names in lower case) and block of each record of a file, compressed or not."""
    if content[:2] == b"\x1f\x8b":
        content = gzip.decompress(content)
    at, view = 0, memoryview(content)
    while at < len(content):
        if content[at : at + 5] != b"WARC/":
            raise ValueError(f"no record at byte {at}")
        end = content.index(b"\r\n\r\n", at)
        lines = content[at:end].decode().split("\r\n")[1:]
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        size = int(headers["content-length"])
        block = view[end + 4 : end + 4 + size]
        at = end + 4 + size
        if len(block) < size or content[at : at + 4] != b"\r\n\r\n":
            raise ValueError(f"record {headers.get('warc-record-id')} is cut")
        at += 4
        yield headers, block


def http(block: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and decoded body of an HTTP response."""
    head, _, body = block.partition(b"\r\n\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode("latin-1").split("\r\n")[1:])}
    return headers, unchunked(body) if "chunked" in headers.get("transfer-encoding", "").lower() else body


FIELDS = "record_id string, record_type string, url string, refers_to string, payload_digest string, payload_bytes long, payload binary"
SEGMENT_FIELDS = "origin string, number int, total long, url string, digest string, block binary"


def plain(uri: str | None) -> str | None:
    return uri.strip("<>") if uri else None


def checked(record_id: str, kind: str, url: str | None, refers_to: str | None, declared: str | None, block: bytes, payloads: bool) -> tuple:
    headers, body = http(block)
    declared = (declared or "").removeprefix("sha256:")
    if kind == "revisit":
        return record_id, kind, url, refers_to, declared, int(headers.get("content-length", 0)), None
    digest = hashlib.sha256(body).hexdigest()
    if declared and digest != declared:
        raise ValueError(f"payload of {record_id} doesn't match its digest")
    return record_id, kind, url, refers_to, digest, len(body), body if payloads else None


KINDS = [pa.string(), pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.binary()]


def table(rows: list[tuple], names: list[str], kinds: list[pa.DataType]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [[]] * len(kinds), kinds, strict=True)], names=names)


def read(spark: SparkSession, folder: str, payloads: bool = True) -> DataFrame:
    """One row per page record of the archives in folder, segments put together again."""
    names, segment_names = [x.split()[0] for x in FIELDS.split(", ")], [x.split()[0] for x in SEGMENT_FIELDS.split(", ")]

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                rows = []
                for h, block in records(content.as_py()):
                    if h["warc-type"] in ("response", "revisit") and "warc-segment-number" not in h:
                        rows.append(checked(plain(h["warc-record-id"]), h["warc-type"], h.get("warc-target-uri"), plain(h.get("warc-refers-to")), h.get("warc-payload-digest"), bytes(block), payloads))
                yield table(rows, names, KINDS)

    def segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                rows = [
                    (plain(h.get("warc-segment-origin-id") or h["warc-record-id"]), int(h["warc-segment-number"]), int(h.get("warc-segment-total-length", -1)), h.get("warc-target-uri"), h.get("warc-payload-digest"), bytes(block))
                    for h, block in records(content.as_py()) if "warc-segment-number" in h
                ]
                yield table(rows, segment_names, [pa.string(), pa.int32(), pa.int64(), pa.string(), pa.string(), pa.binary()])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                origin, total, parts = (batch.column(k)[i].as_py() for k in range(3))
                by_number = {p["number"]: p for p in parts}  # rows that were archived twice have each segment twice
                copies = sum(p["number"] == 1 for p in parts)
                if sorted(by_number) != list(range(1, len(by_number) + 1)) or not copies:
                    raise ValueError(f"segments of {origin} are missing")
                block = b"".join(by_number[k]["block"] for k in sorted(by_number))
                if len(block) != total:
                    raise ValueError(f"segments of {origin} have {len(block)} of {total} bytes")
                row = checked(origin, "response", by_number[1]["url"], None, by_number[1]["digest"], block, payloads)
                yield table([row] * copies, names, KINDS)

    files = spark.read.format("binaryFile").load(folder).select("content")
    parts = files.mapInArrow(segments, SEGMENT_FIELDS)
    grouped = parts.groupBy("origin").agg(F.max("total").alias("total"), F.collect_list(F.struct("number", "url", "digest", "block")).alias("parts"))
    return files.mapInArrow(whole, FIELDS).unionByName(grouped.mapInArrow(joined, FIELDS))


def page_id_of(name: str):
    """The page id inside a record id that write() made."""
    return F.element_at(F.split(F.col(name), ":"), 3).try_cast("long")


def round_trip(pages: DataFrame, **options) -> DataFrame:
    """Writes the archives in the shared folder and reads their records back, without payloads."""
    folder = common.new_folder(pages.sparkSession, "archives")
    write(pages, folder, **options)
    return read(pages.sparkSession, folder, payloads=False)
