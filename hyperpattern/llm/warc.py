"""WARC archives: writing records in segments, and putting them together again.

Archives are gzip members, one for each record, held as rows (archive, content) of a written table, so that any store
Spark writes to will do. Reading parses the members, groups continuation records by the id of the record they continue,
orders them by segment number, verifies numbers and total length, and decodes chunked transfer framing.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import small, table, text_or_empty, written

SEGMENT, CHUNK, ARCHIVE = 32_768, 8_192, 4 << 20
CRLF = b"\r\n"
#: Extension fields that hold the id of a page, and of the page that a revisit refers to.
PAGE, REFERS_TO_PAGE = "WARC-X-Page-ID", "WARC-X-Refers-To-Page-ID"
SCHEMA = "archive string, content binary"


def digest32(payload: bytes) -> str:
    """Bare upper-case base32 of SHA-1."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = ["WARC/1.1", *(f"{k}: {v}" for k, v in [*headers, ("Content-Length", str(len(block)))])]
    return "\r\n".join(lines).encode() + CRLF + CRLF + block + CRLF + CRLF


def chunked(payload: bytes, size: int = CHUNK) -> bytes:
    parts = [payload[i : i + size] for i in range(0, len(payload), size)]
    return b"".join(b"%x\r\n%s\r\n" % (len(p), p) for p in parts) + b"0\r\n\r\n"


def unchunked(body: bytes) -> bytes:
    """Raises ValueError on broken framing; extensions and trailers are skipped."""
    out, p = [], 0
    while True:
        end = body.find(CRLF, p)
        if end < 0:
            raise ValueError("chunk size line is missing")
        n = int(body[p:end].split(b";")[0].strip(), 16)
        p = end + 2
        if n == 0:
            return b"".join(out)
        if body[p + n : p + n + 2] != CRLF:
            raise ValueError("chunk is cut short")
        out.append(body[p : p + n])
        p += n + 2


def http_block(payload: bytes) -> bytes:
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload)


def http_payload(block: bytes) -> bytes:
    head, _, body = block.partition(CRLF + CRLF)
    headers = {k.strip().lower(): v.strip().lower() for k, _, v in (line.partition(b":") for line in head.split(CRLF)[1:])}
    return unchunked(body) if headers.get(b"transfer-encoding") == b"chunked" else body


def record_id(page_id, digest: str, ordinal: str = "") -> str:
    """Unique by page id and payload; rows that repeat both are told apart by an ordinal."""
    return f"<urn:page:{'' if page_id is None else page_id}:{digest}{ordinal and ':' + ordinal}>"


def page_records(page_id, url: str, payload: bytes, digest: str, origin, segment: int = SEGMENT, ordinal: str = "") -> Iterator[bytes]:
    """A revisit of `origin`, or a response in segments of at most `segment` bytes.

    The page id travels in a field of its own (none if null). A revisit names its response by page id and payload; should
    that response be repeated, all of its records fit, since their payloads are equal.
    """
    name = record_id(page_id, digest, ordinal)
    common = [("WARC-Target-URI", url), ("WARC-Date", "2024-01-01T00:00:00Z")] + [(PAGE, str(page_id))] * (page_id is not None)
    if origin is not None:
        yield record([("WARC-Type", "revisit"), ("WARC-Record-ID", name), *common, (REFERS_TO_PAGE, str(origin)), ("WARC-Refers-To", record_id(origin, digest)), ("WARC-Payload-Digest", f"sha1:{digest}"), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")], b"")
        return
    block = http_block(payload)
    parts = [block[i : i + segment] for i in range(0, len(block), segment)]
    first = [("WARC-Type", "response"), ("WARC-Record-ID", name), *common, ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    yield record(first + [("WARC-Segment-Number", "1")] * (len(parts) > 1), parts[0])
    for k, part in enumerate(parts[1:], 2):
        last = [("WARC-Segment-Total-Length", str(len(block)))] if k == len(parts) else []
        yield record([("WARC-Type", "continuation"), ("WARC-Record-ID", f"{name[:-1]}:segment-{k}>"), *common, ("WARC-Segment-Origin-ID", name), ("WARC-Segment-Number", str(k)), *last], part)


def one_line(text: str | None) -> str:
    return " ".join((text or "").split())


def write_archives(pages: DataFrame, segment: int = SEGMENT) -> DataFrame:
    """pages: page_id, url, html, origin (null: a response), repeated (its page id and payload occur again). Rows archive, content.

    An archive holds records of one input partition up to ARCHIVE bytes. Repeated rows get a random ordinal, which need only
    be unique in the archives that are kept: a task that runs twice leaves one set of them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        members: list[bytes] = []
        size = made = 0

        def flush() -> pa.RecordBatch:
            nonlocal size, made
            content = b"".join(members)
            members.clear()
            size, made = 0, made + 1
            return pa.RecordBatch.from_arrays([pa.array([f"{hashlib.sha1(content).hexdigest()}.warc.gz"]), pa.array([content], pa.binary())], names=["archive", "content"])

        for batch in batches:
            for page_id, url, html, origin, repeated in zip(*(batch.column(c) for c in range(5)), strict=True):
                payload = (html.as_py() or "").encode()
                ordinal = uuid.uuid4().hex if repeated.as_py() else ""
                for r in page_records(page_id.as_py(), one_line(url.as_py()), payload, digest32(payload), origin.as_py(), segment, ordinal):
                    members.append(gzip.compress(r, 1, mtime=0))
                    size += len(members[-1])
                if size >= ARCHIVE:
                    yield flush()
        if members:
            yield flush()

    return pages.select("page_id", "url", "html", "origin", "repeated").mapInArrow(run, SCHEMA)


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    head, mark, rest = raw.partition(CRLF + CRLF)
    lines = head.decode().split("\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    n = int(headers["content-length"])
    if not lines[0].startswith("WARC/") or not mark or rest[n:] != CRLF + CRLF:
        raise ValueError("not a WARC record")
    return headers, rest[:n]


RECORDS = "record_id string, page_id long, record_type string, digest string, refers_to long, segment int, total long, block binary"


def read_archives(archives: DataFrame) -> DataFrame:
    """One row for each record. record_id of a continuation is that of the record it continues; segment is null for whole records."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split(" ")[0] for x in RECORDS.split(", ")]
        kinds = (pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.binary())

        def made(out: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

        for batch in batches:
            for content in batch.column("content"):
                out, size = [], 0
                raw = content.as_py()
                view = memoryview(raw)
                p = 0
                while p < len(view):
                    z = zlib.decompressobj(31)
                    parts, at = [], p
                    while not z.eof:
                        if at >= len(view):
                            raise ValueError("archive ends inside a record")
                        parts.append(z.decompress(view[at : at + 65_536]))
                        at += 65_536
                    p = min(at, len(view)) - len(z.unused_data)
                    h, block = parse(b"".join(parts))
                    number = int(h["warc-segment-number"]) if "warc-segment-number" in h else None
                    total = int(h["warc-segment-total-length"]) if "warc-segment-total-length" in h else None
                    page, other = (int(h[k.lower()]) if k.lower() in h else None for k in (PAGE, REFERS_TO_PAGE))
                    out.append((h.get("warc-segment-origin-id", h["warc-record-id"]), page, h["warc-type"], h.get("warc-payload-digest", "").removeprefix("sha1:") or None, other, number, total, block))
                    size += len(block)
                    if size >= ARCHIVE:
                        yield made(out)
                        out, size = [], 0
                if out:
                    yield made(out)

    return archives.select("archive", "content").mapInArrow(run, RECORDS)


def reassembled(records: DataFrame) -> DataFrame:
    """record_id, page_id, record_type, digest, refers_to, block, complete: segments joined in order; incomplete ones keep what there is, with complete false."""
    keep = ["record_id", "page_id", "record_type", "digest", "refers_to", "block"]
    whole = records.where("segment is null").select(*keep, F.lit(True).alias("complete"))
    parts = F.array_sort(F.collect_list(F.struct("segment", F.decode("block", "ISO-8859-1").alias("bytes"))))
    grouped = records.where("segment is not null").groupBy("record_id").agg(
        F.max("page_id").alias("page_id"),
        F.max(F.when(F.col("segment") == 1, F.col("record_type"))).alias("record_type"),
        F.max("digest").alias("digest"),
        F.max("refers_to").alias("refers_to"),
        F.max("total").alias("total"),
        parts.alias("parts"),
    )
    # bytes as characters of one byte each, so that any number of segments is joined in one copy
    block = F.encode(F.array_join(F.transform("parts", lambda x: x["bytes"]), ""), "ISO-8859-1")
    numbered = F.transform("parts", lambda x: x["segment"]) == F.sequence(F.lit(1), F.size("parts"))
    joined = grouped.withColumn("block", block).select(*keep, (numbered & F.coalesce(F.col("total") == F.octet_length("block"), F.lit(False))).alias("complete"))
    return whole.unionByName(joined)


def payloads(records: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to, one row for each record: payloads taken out of HTTP and its framing, digests recomputed from the bytes.

    A broken frame, an incomplete record or a digest that disagrees with the header fails the job.
    """
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, digests = [], []
            for rid, kind, said, block, complete in zip(*(batch.column(c) for c in ("record_id", "record_type", "digest", "block", "complete")), strict=True):
                if kind.as_py() == "revisit":
                    sizes.append(None)
                    digests.append(said.as_py())
                    continue
                if not complete.as_py():
                    raise ValueError(f"{rid.as_py()}: segments are missing")
                body = http_payload(block.as_py())
                sizes.append(len(body))
                digests.append(digest32(body))
                if digests[-1] != said.as_py():
                    raise ValueError(f"{rid.as_py()}: digest differs")
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), pa.array(sizes, pa.int64()), pa.array(digests, pa.string()), batch.column("record_type"), batch.column("refers_to")], names=[x.split(" ")[0] for x in schema.split(", ")])

    return records.mapInArrow(run, schema)


def with_origins(pages: DataFrame) -> DataFrame:
    """pages with `origin`: the smallest page_id of equal payloads for the other pages, null for that page itself; and `repeated`: page_id and payload occur again.

    Null ids come last: they are responses only if no page with an id has their payload.
    """
    marked = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.sha1(F.encode(text_or_empty("html"), "UTF-8")).alias("_digest"))
    by_page = marked.groupBy("_digest", "page_id").agg(F.count("*").alias("_n"))
    # a payload that occurs once has no row here
    groups = written(by_page.groupBy("_digest").agg(F.min("page_id").alias("_least"), F.sum("_n").alias("_all"), F.max("_n").alias("_most")).where("_all > 1").select("_digest", "_least", "_most"), "equal-payloads")
    joined = marked.join(small(groups), "_digest", "left")
    return joined.select("page_id", "url", "html", F.when(~F.col("_least").eqNullSafe(F.col("page_id")), F.col("_least")).alias("origin"), F.coalesce(F.col("_most") > 1, F.lit(False)).alias("repeated"))


def op3_warc_reassembly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page written to archives and read back: one record and one row for each row of pages, repeated ids and null ids too."""
    return round_trip(table(spark, sf_dir, "pages"))


def round_trip(pages: DataFrame, segment: int = SEGMENT) -> DataFrame:
    archives = written(write_archives(with_origins(pages), segment), "archives")
    out = written(payloads(reassembled(read_archives(archives))), "payloads")
    # a revisit holds no payload: its size is that of the response it refers to, whose digest must be equal
    revisits = out.where("record_type = 'revisit'").drop("payload_bytes")
    asked = revisits.select(F.col("refers_to").alias("page_id"), "payload_digest").distinct()
    given = out.where("record_type = 'response'").join(asked, ["page_id", "payload_digest"], "left_semi")
    origins = written(given.groupBy(F.col("page_id").alias("refers_to"), "payload_digest").agg(F.max("payload_bytes").alias("payload_bytes")), "origins")
    revisits = revisits.join(small(origins), ["refers_to", "payload_digest"], "left")
    return out.where("record_type = 'response'").unionByName(revisits.select(*out.columns))
