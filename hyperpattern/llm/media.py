"""Media columns: signature sniffing.

One Aho-Corasick automaton over all magic bytes finds every place in a byte string at which a known format may begin; a
validator of that format then walks its structure and says how long it is, or that it isn't one. The confirmed type at
offset 0 corrects a declared type; confirmed media elsewhere are carved out. Texts are carried as 8-bit mono WAV.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .shared import table

#: Fixed values of the formats: type, magic bytes, where in the file they stand.
MAGIC = [
    ("image/png", b"\x89PNG\r\n\x1a\n", 0),
    ("image/jpeg", b"\xff\xd8\xff", 0),
    ("image/gif", b"GIF87a", 0),
    ("image/gif", b"GIF89a", 0),
    ("image/bmp", b"BM", 0),
    ("audio/wav", b"WAVE", 8),
    ("image/webp", b"WEBP", 8),
    ("audio/flac", b"fLaC", 0),
    ("audio/ogg", b"OggS", 0),
    ("audio/mpeg", b"ID3", 0),
    ("video/mp4", b"ftyp", 4),
    ("application/pdf", b"%PDF-", 0),
    ("application/zip", b"PK\x03\x04", 0),
    ("application/gzip", b"\x1f\x8b\x08", 0),
]


def _png(b: bytes, at: int) -> int:
    p, first = at + 8, True
    while p + 12 <= len(b):
        n, kind = struct.unpack_from(">I4s", b, p)
        if p + 12 + n > len(b) or first and (kind, n) != (b"IHDR", 13) or zlib.crc32(b[p + 4 : p + 8 + n]) != struct.unpack_from(">I", b, p + 8 + n)[0]:
            return 0
        p, first = p + 12 + n, False
        if kind == b"IEND":
            return p - at
    return 0


def _jpeg(b: bytes, at: int) -> int:
    p, scanned = at + 2, False
    while p + 4 <= len(b):
        if b[p] != 0xFF:
            return 0
        m = b[p + 1]
        if m == 0xFF:
            p += 1
            continue
        if m == 0xD9:
            return p + 2 - at if scanned else 0
        if m == 0 or m == 1 or 0xD0 <= m <= 0xD8:
            return 0
        p += 2 + struct.unpack_from(">H", b, p + 2)[0]
        if m == 0xDA:  # entropy-coded bytes run to the next marker that is neither stuffing nor a restart
            scanned = True
            while (p := b.find(b"\xff", p)) >= 0 and p + 1 < len(b) and (b[p + 1] == 0 or 0xD0 <= b[p + 1] <= 0xD7):
                p += 2
            if p < 0:
                return 0
    return p + 2 - at if scanned and b[p : p + 2] == b"\xff\xd9" else 0


def _gif(b: bytes, at: int) -> int:
    def blocks(p: int) -> int:
        while p < len(b) and b[p]:
            p += 1 + b[p]
        return p + 1

    if at + 13 > len(b):
        return 0
    p, images = at + 13 + (3 << (b[at + 10] & 7) + 1 if b[at + 10] & 0x80 else 0), 0
    while p < len(b):
        if b[p] == 0x3B:
            return p + 1 - at if images else 0
        if b[p] == 0x21:
            p = blocks(p + 2)
        elif b[p] == 0x2C and p + 10 <= len(b):
            images += 1
            p = blocks(p + 11 + (3 << (b[p + 9] & 7) + 1 if b[p + 9] & 0x80 else 0))
        else:
            return 0
    return 0


def _bmp(b: bytes, at: int) -> int:
    if at + 26 > len(b):
        return 0
    size, zero, offset, header = struct.unpack_from("<IIII", b, at + 2)
    return size if zero == 0 and header in (12, 40, 52, 56, 108, 124) and 14 + header <= offset <= size and at + size <= len(b) else 0


def _riff(kind: bytes, first: tuple[bytes, ...]) -> Callable[[bytes, int], int]:
    def walk(b: bytes, at: int) -> int:
        if b[at : at + 4] != b"RIFF" or b[at + 8 : at + 12] != kind or at + 20 > len(b):
            return 0
        end = at + 8 + struct.unpack_from("<I", b, at + 4)[0]
        p = at + 12
        if end > len(b) or b[p : p + 4] not in first:
            return 0
        while p + 8 <= end:
            p += 8 + (n := struct.unpack_from("<I", b, p + 4)[0]) + n % 2
        return end - at if p == end else 0

    return walk


def _flac(b: bytes, at: int) -> int:
    p, first = at + 4, True
    while p + 4 <= len(b):
        head, n = b[p], int.from_bytes(b[p + 1 : p + 4], "big")
        if first and (head & 0x7F != 0 or n != 34) or p + 4 + n > len(b):
            return 0
        p, first = p + 4 + n, False
        if head & 0x80:
            return len(b) - at if b[p : p + 1] == b"\xff" else 0
    return 0


def _ogg(b: bytes, at: int) -> int:
    p, pages = at, 0
    while b[p : p + 5] == b"OggS\0" and p + 27 <= len(b) and p + 27 + b[p + 26] <= len(b):
        end = p + 27 + b[p + 26] + sum(b[p + 27 : p + 27 + b[p + 26]])
        if end > len(b):
            break
        pages, last, p = pages + 1, b[p + 5] & 4, end
        if last:
            return p - at
    return p - at if pages else 0


def _mp3(b: bytes, at: int) -> int:
    if at + 10 > len(b) or b[at + 3] > 4 or any(x & 0x80 for x in b[at + 6 : at + 10]):
        return 0
    n = 10 + sum(x << 7 * (3 - i) for i, x in enumerate(b[at + 6 : at + 10]))
    return len(b) - at if b[at + n : at + n + 1] == b"\xff" and b[at + n + 1 : at + n + 2] >= b"\xe0" else 0


def _mp4(b: bytes, at: int) -> int:
    p, kinds = at, set()
    while p + 8 <= len(b):
        n, kind = struct.unpack_from(">I4s", b, p)
        if n < 8 or p + n > len(b) or not kind.isalnum():
            break
        kinds.add(kind)
        p += n
    return p - at if {b"ftyp", b"moov"} <= kinds else 0


def _pdf(b: bytes, at: int) -> int:
    if not b[at + 5 : at + 6].isdigit() or b.find(b"startxref", at) < 0:
        return 0
    end, following = b.find(b"%%EOF", at), b.find(b"%PDF-", at + 5)
    while end >= 0 and 0 <= (later := b.find(b"%%EOF", end + 5)) and (following < 0 or later < following):
        end = later  # later updates of the file end in their own marks
    return end + 5 - at if end >= 0 else 0


def _zip(b: bytes, at: int) -> int:
    p = b.find(b"PK\x05\x06", at)
    while p >= 0 and p + 22 <= len(b):
        size, start, note = struct.unpack_from("<IIH", b, p + 12)
        if at + start + size == p and p + 22 + note <= len(b) and (size == 0 or b[at + start : at + start + 4] == b"PK\x01\x02"):
            return p + 22 + note - at
        p = b.find(b"PK\x05\x06", p + 4)
    return 0


def _gzip(b: bytes, at: int) -> int:
    """Inflates the member in bounded steps; its trailer must agree."""
    z, p, step = zlib.decompressobj(31), at, 1 << 16
    try:
        while not z.eof and p < len(b):
            z.decompress(b[p : p + step])
            p += step
    except zlib.error:
        return 0
    return min(p, len(b)) - len(z.unused_data) - at if z.eof else 0


VALIDATORS: dict[str, Callable[[bytes, int], int]] = {
    "image/png": _png,
    "image/jpeg": _jpeg,
    "image/gif": _gif,
    "image/bmp": _bmp,
    "audio/wav": _riff(b"WAVE", (b"fmt ", b"JUNK", b"bext", b"LIST")),
    "image/webp": _riff(b"WEBP", (b"VP8 ", b"VP8L", b"VP8X")),
    "audio/flac": _flac,
    "audio/ogg": _ogg,
    "audio/mpeg": _mp3,
    "video/mp4": _mp4,
    "application/pdf": _pdf,
    "application/zip": _zip,
    "application/gzip": _gzip,
}


@lru_cache(maxsize=1)
def automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for kind, magic, offset in MAGIC:
        a.add_word(magic.decode("latin-1"), (kind, offset + len(magic) - 1))
    a.make_automaton()
    return a


def sniff(b: bytes) -> list[tuple[str, int, int]]:
    """(type, offset, length) of all confirmed media, outermost first: what lies inside a found one isn't listed, save in a container from offset 0, whose contents are."""
    found, end = [], 0
    for last, (kind, back) in automaton().iter(b.decode("latin-1")):
        at = last - back
        if at >= end and at >= 0 and (n := VALIDATORS[kind](b, at)):
            found.append((kind, at, n))
            end = at + n if at else 12
    return found


def corrected_type(declared: str | None, found: list[tuple[str, int, int]]) -> str:
    """The confirmed type at offset 0; without one, a declared type that sniffing can refute counts as unknown."""
    if found and found[0][1] == 0:
        return found[0][0]
    return "application/octet-stream" if not declared or declared in VALIDATORS else declared


def sniff_media(df: DataFrame, media: str, declared: str | None = None) -> DataFrame:
    """df with media_type, media_length, type_corrected and carved (array of type, offset, length, bytes) from a binary column.

    A null counts as empty bytes: unknown type, nothing carved. Columns of df with those names are replaced.
    """
    own = {"media_type", "media_length", "type_corrected", "carved"}
    keep = [f for f in df.schema if f.name not in own]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in keep) + ", media_type string, media_length long, type_corrected boolean, carved array<struct<type:string,offset:long,length:long,bytes:binary>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kinds, sizes, fixed, carved = [], [], [], []
            said = batch.column(declared).to_pylist() if declared else [None] * batch.num_rows
            for b, old in zip(batch.column(media), said, strict=True):
                b = b.as_py() or b""
                found = sniff(b)
                kinds.append(corrected_type(old, found))
                sizes.append(found[0][2] if found and found[0][1] == 0 else 0)
                fixed.append(old is not None and old != kinds[-1])
                carved.append([{"type": k, "offset": at, "length": n, "bytes": b[at : at + n]} for k, at, n in found if at])
            kind = pa.list_(pa.struct([("type", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("bytes", pa.binary())]))
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in keep), pa.array(kinds, pa.string()), pa.array(sizes, pa.int64()), pa.array(fixed, pa.bool_()), pa.array(carved, kind)], names=[*(f.name for f in keep), "media_type", "media_length", "type_corrected", "carved"])

    return df.mapInArrow(run, schema)


RATE, FRAME = 8000, 192


def to_wav(payload: bytes) -> bytes:
    """8-bit mono PCM; a chunk of odd length would be padded, but a payload is a multiple of 192."""
    return struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload), b"WAVE", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8, b"data", len(payload)) + payload


def wav_samples(media: bytes) -> bytes:
    """The data chunk, found by walking the chunks."""
    p = 12
    while media[p : p + 4] != b"data":
        p += 8 + struct.unpack_from("<I", media, p + 4)[0]
    return media[p + 8 : p + 8 + struct.unpack_from("<I", media, p + 4)[0]]


def padded(raw: bytes) -> bytes:
    return raw + b" " * (-len(raw) % FRAME or (0 if raw else FRAME))


def describe(media: bytes, samples: bytes) -> str:
    """Features of stored media: sniffed type, sample statistics, energy by quarter, and what is embedded."""
    found = sniff(media)
    x = np.frombuffer(samples, np.uint8)
    hist = np.bincount(x, minlength=256)
    total, square = int(hist @ np.arange(256)), int(hist @ np.arange(256) ** 2)
    up = x >= 128
    crossings = int(np.count_nonzero(up[1:] != up[:-1]))
    quarters = ",".join(str(int(np.add.reduce(q, dtype=np.int64))) for q in np.array_split(x, 4))
    inside = ",".join(f"{k}@{at}+{n}" for k, at, n in found if at) or "none"
    return f"{corrected_type(None, found)};rate={RATE};samples={len(x)};min={int(np.flatnonzero(hist)[0])};max={int(np.flatnonzero(hist)[-1])};sum={total};square={square};crossings={crossings};distinct={int(np.count_nonzero(hist))};quarters={quarters};embedded={inside}"


def store_texts(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media: each text (null: empty) as WAV."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                raw = [(t.as_py() or "").encode() for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(b) for b in raw], pa.int64()), pa.array([to_wav(padded(b)) for b in raw], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, media binary")


def read_media(stored: DataFrame) -> DataFrame:
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for m in batch.column(2):
                media = m.as_py()
                samples = wav_samples(media)
                out.append((len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-16:]), len(media), hashlib.sha256(media).hexdigest(), describe(media, samples)))
            columns = list(zip(*out, strict=True)) or [()] * 6
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=[x.split(" ")[0] for x in schema.split(", ")])

    return stored.mapInArrow(run, schema)


def op1_media_sniffing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text of documents as stored media, read back, sniffed and described."""
    return read_media(store_texts(table(spark, sf_dir, "documents")))
