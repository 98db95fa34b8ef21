"""Repeated byte strings by a difference-cover sample.

A byte goes if a string of LENGTH bytes over it also starts elsewhere. The residues of a difference cover of period v are
such that for any two places some shift below v brings both to sampled places. So if two strings of LENGTH bytes are
equal, two sampled tuples of LENGTH - v + 1 bytes, equally far inside, are equal too. Sampled tuples are named by
fingerprints and sorted; equal neighbours mark the only places near which a repeated string can start. There the
remaining starts are merged: runs of starts that share the least 8-gram of their strings are equal or not together, and
within what is left starts are sorted by the fingerprint of all LENGTH bytes, neighbours are compared, and those that
seem equal are compared byte by byte.

Names are fingerprints in place of ranks, since only equality is asked for: 48 bits and the bucket for samples, which can
only add places to look at. Equal texts are one text throughout. A name that many texts have is met once for each chunk of
texts, and a bucket with more starts than PER_BUCKET is dealt out over several tasks, which pass on one start of each
string to be met in a second round.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import small, table, text_or_empty, written

LENGTH, GRAM = 400, 8
#: Entries that one bucket is meant to hold.
PER_BUCKET = 250_000
#: Bytes of text in a chunk, at which names are first met.
CHUNK = 1 << 20
U = np.uint64


@lru_cache(maxsize=4)
def difference_cover(length: int) -> tuple[int, tuple[int, ...]]:
    """(period, residues): the points of a line of the projective plane of the largest prime order q with period q * q + q + 1 up to half the length.

    Powers of a primitive element x of the field of q**3 elements run through the points; those without x**2 are a line,
    and every difference modulo the period occurs between two of them exactly once.
    """
    prime = lambda n: n > 1 and all(n % d for d in range(2, n))
    q = max((n for n in range(2, length) if n * n + n + 1 <= length // 2 and prime(n)), default=0)
    if not q:
        return 1, (0,)
    period = q * q + q + 1
    for a, b, c in ((a, b, c) for c in range(1, q) for b in range(q) for a in range(q)):
        power, line, order = (1, 0, 0), [], 0
        while True:
            if order < period and power[2] == 0:
                line.append(order)
            lo, mid, hi = power
            power = (c * hi % q, (lo + b * hi) % q, (mid + a * hi) % q)  # times x, with x**3 = a x**2 + b x + c
            order += 1
            if power == (1, 0, 0) or order > q**3:
                break
        if order == q**3 - 1:
            return period, tuple(line)
    raise AssertionError("no primitive polynomial")


def _places(starts: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    """For each byte of joined texts: its place in its text, and the bytes of the text from there on."""
    lengths = np.diff(starts)
    at = np.arange(total, dtype=np.int32) - np.repeat(starts[:-1].astype(np.int32), lengths)
    return at, np.repeat(lengths.astype(np.int32), lengths) - 1 - at


def _lists(values: np.ndarray, counts: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(values))


def grams(b: np.ndarray, width: int = GRAM) -> np.ndarray:
    """The `width` (at most 8) bytes from each place on as a mixed number; zeros follow the last byte."""
    raw = np.concatenate([b, np.zeros(8, np.uint8)])
    x = np.ndarray((len(b),), "<u8", raw.data, strides=(1,)).astype(U)
    return K.mixed((x & U((1 << 8 * width) - 1)) + U(K.BASE))


def gram_sums(mixed: np.ndarray) -> np.ndarray:
    """Prefix sums for hashes of stretches of mixed grams. Sums over bytes themselves agree for some strings of a few symbols whatever their values; those over mixed grams don't."""
    out = np.zeros(len(mixed) + 1, U)
    np.cumsum(mixed * K.POWERS.upto(len(mixed) + 1)[0][: len(mixed)], out=out[1:])
    return out


def sampled_names(texts: DataFrame, length: int, buckets: int) -> DataFrame:
    """bucket, chunk, names (48 bits each), keys, counts, places: sampled tuples of a chunk of texts (named by its first key), dealt out by name.

    A name that a chunk has several times goes to its bucket once. All places of such names are a row of their own, with
    null names: they are known to be repeated.
    """
    period, residues = difference_cover(length)
    tuple_bytes = length - period + 1
    width = min(GRAM, tuple_bytes)
    schema = "bucket int, chunk binary, names binary, keys array<binary>, counts array<int>, places binary"
    kinds = (pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.binary()), pa.list_(pa.int32()), pa.binary())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chosen = np.zeros(period, bool)
        chosen[list(residues)] = True
        for batch in batches:
            for first, n in K.parts(batch.column(1), CHUNK):
                part = batch.slice(first, n)
                keys = part.column(0).to_pylist()
                b, starts = K.joined(part.column(1))
                at, left = _places(starts, len(b))
                s = np.flatnonzero(chosen[at % period] & (left >= tuple_bytes))
                if not len(s):
                    continue
                h = K.mixed(K.stretch_hashes(gram_sums(grams(b, width)), s, s + tuple_bytes - width + 1))
                _, one_of, which, times = np.unique(h, return_index=True, return_inverse=True, return_counts=True)
                out = []

                def add(bucket: int, own: np.ndarray, named: bool) -> None:
                    """own: places in s, in the order of texts."""
                    who, counts = np.unique(np.searchsorted(starts, s[own], side="right") - 1, return_counts=True)  # noqa: B023
                    names = h[own].view(np.uint8).reshape(-1, 8)[:, :6].tobytes() if named else None  # noqa: B023
                    places = at[s[own]].astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()  # noqa: B023  planes of bytes compress
                    out.append((bucket, keys[0], names, [keys[i] for i in who], counts.tolist(), places))  # noqa: B023

                again = np.flatnonzero(times[which] > 1)
                if len(again):
                    add(int(h[again[0]] % U(buckets)), again, False)
                one_of.sort()
                bucket = ((h[one_of] >> U(48)) % U(buckets)).astype(np.int64) if buckets < 1 << 16 else (K.mixed(h[one_of]) % U(buckets)).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                edge = np.searchsorted(bucket[order], np.arange(buckets + 1)) if buckets < len(order) else np.flatnonzero(np.diff(bucket[order], prepend=-1, append=-1))
                for i, j in zip(edge[:-1], edge[1:], strict=True):
                    if i < j:
                        add(int(bucket[order[i]]), one_of[order[i:j]], True)
                yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), kinds, strict=True)], names=["bucket", "chunk", "names", "keys", "counts", "places"])

    return texts.select("k", "text").mapInArrow(run, schema)


REPEATED = "chunk binary, keys array<binary>, counts array<int>, places binary"


def _numbers(lists: pa.ChunkedArray) -> np.ndarray:
    return np.concatenate([np.asarray(x.values) for x in lists])


def _repeated_names(group: pa.Table) -> pa.Table:
    """Of each row of the bucket, the samples whose name occurs twice or more in the bucket; rows of known repeats as they are."""
    raw = [np.frombuffer(x.as_buffer(), np.uint8).reshape(-1, 6) if x.is_valid else np.zeros((0, 6), np.uint8) for x in group.column("names")]
    name = np.zeros((sum(map(len, raw)), 8), np.uint8)
    if len(name):
        name[:, :6] = np.concatenate(raw)
    name = name.view(U).ravel()
    order = np.argsort(name, kind="stable")
    same = name[order][1:] == name[order][:-1]
    again = np.zeros(len(name), bool)
    again[order[1:][same]] = True
    again[order[:-1][same]] = True
    out, at = [], 0
    for own, chunk, keys, counts, places in zip(raw, *(group.column(c) for c in ("chunk", "keys", "counts", "places")), strict=True):
        counts = np.asarray(counts.values)
        named = group.num_rows and len(own) > 0
        hit = again[at : at + len(own)] if named else np.ones(int(counts.sum()), bool)
        at += len(own)
        if hit.any():
            place = np.ascontiguousarray(np.frombuffer(places.as_buffer(), np.uint8).reshape(4, -1).T).view("<u4").ravel()
            of_key = np.add.reduceat(hit.astype(np.int32), np.concatenate([[0], np.cumsum(counts)[:-1]]))
            has = np.flatnonzero(of_key)
            out.append((chunk.as_py(), keys.values.take(pa.array(has)).to_pylist(), of_key[has].tolist(), place[hit].astype("<i4").tobytes()))
    kinds = (pa.binary(), pa.list_(pa.binary()), pa.list_(pa.int32()), pa.binary())
    columns = list(zip(*out, strict=True)) or [()] * 4
    return pa.table({n: pa.array(c, k) for n, c, k in zip(("chunk", "keys", "counts", "places"), columns, kinds, strict=True)})


def _stretches(period: int):
    def run(group: pa.Table) -> pa.Table:
        """k, lo, hi for the texts of a chunk: stretches [lo, hi) of starts from which a repeated sample is less than a period away."""
        keys = pa.concat_arrays([x.values for x in group.column("keys")])
        names, who = np.unique(np.frombuffer(b"".join(keys.to_pylist()), "V16"), return_inverse=True)
        owner = np.repeat(who, _numbers(group.column("counts")))
        place = np.concatenate([np.frombuffer(x.as_buffer(), "<i4") for x in group.column("places")]).astype(np.int64)
        order = np.lexsort((place, owner))
        owner, place = owner[order], place[order]
        new = np.ones(len(place), bool)
        new[1:] = (owner[1:] != owner[:-1]) | (np.diff(place) > period)
        lo = np.maximum(place[new] - period + 1, 0).astype(np.int32)
        hi = (place[np.append(np.flatnonzero(new)[1:], len(place)) - 1] + 1).astype(np.int32)
        counts = np.bincount(owner[new], minlength=len(names))
        return pa.table({"k": pa.array([x.tobytes() for x in names], pa.binary()), "lo": _lists(lo, counts), "hi": _lists(hi, counts)})

    return run


def _least_ahead(x: np.ndarray, width: int) -> np.ndarray:
    """The minimum of `width` entries from each place (fewer at the end)."""
    have = 1
    while have < width:
        step = min(have, width - have)
        x = np.minimum(x, np.concatenate([x[step:], np.full(min(step, len(x)), ~U(0))])[: len(x)])
        have += step
    return x


def runs_of_starts(texts: DataFrame, length: int) -> DataFrame:
    """least, k, at, bytes: stretches of starts to check whose strings have the same least 8-gram; bytes covers all their strings. texts: k, text, lo, hi."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, n in K.parts(batch.column(1)):
                part = batch.slice(first, n)
                b, starts = K.joined(part.column(1))
                raw = b.tobytes()
                at, left = _places(starts, len(b))
                check = np.zeros(len(b) + 1, np.int32)
                for side, step in ((2, 1), (3, -1)):
                    lists = part.column(side)
                    where = np.repeat(starts[:-1], [len(x) for x in lists])
                    to = np.minimum(np.concatenate([np.asarray(x.values) for x in lists]), np.repeat(np.diff(starts), [len(x) for x in lists]))
                    np.add.at(check, where + to, step)
                check = (np.cumsum(check)[:-1] > 0) & (left >= length)
                least = _least_ahead(grams(b), length - GRAM + 1)
                p = np.flatnonzero(check)
                new = np.ones(len(p), bool)
                new[1:] = (np.diff(p) != 1) | (least[p][1:] != least[p][:-1])
                lo = p[new]
                hi = p[np.append(np.flatnonzero(new)[1:], len(p)) - 1] if len(p) else lo
                text = np.searchsorted(starts, lo, side="right") - 1
                pieces = pa.array([raw[i : j + length] for i, j in zip(lo.tolist(), hi.tolist(), strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(least[lo].view(np.int64)), part.column(0).take(pa.array(text)), pa.array(at[lo].astype(np.int32)), pieces], names=["least", "k", "at", "bytes"])

    return texts.select("k", "text", "lo", "hi").mapInArrow(run, "least long, k binary, at int, bytes binary")


def _strings(pieces: pa.Array, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(fingerprint, piece, start in it, start in bytes, bytes) of all strings of `length` bytes in pieces."""
    b, starts = K.joined(pieces)
    count = np.diff(starts) - length  # a piece ends in a zero byte of ours
    piece = np.repeat(np.arange(len(count), dtype=np.int32), count)
    within = (np.arange(len(piece)) - np.repeat(np.cumsum(count) - count, count)).astype(np.int32)
    s = starts[piece] + within
    width = min(GRAM, length)
    return K.mixed(K.stretch_hashes(gram_sums(grams(b, width)), s, s + length - width + 1)), piece, within, s, b


def _equal_neighbours(name: np.ndarray, s: np.ndarray, b: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(has an equal string elsewhere, is the first of its likes): starts are sorted by name, neighbours of one name are compared by their bytes.

    A pair whose two strings begin one byte after those of another equal pair differs at most in the last byte; other
    pairs are compared whole. Should strings of one name differ, those of that name are told apart by their bytes.
    """
    order = np.argsort(name, kind="stable")
    x, y = order[:-1], order[1:]
    same = name[x] == name[y]
    x, y = x[same], y[same]
    at = np.argsort(y, kind="stable")
    x, y = x[at], y[at]
    follows = np.zeros(len(x), bool)
    follows[1:] = (s[x][1:] == s[x][:-1] + 1) & (s[y][1:] == s[y][:-1] + 1)
    equal = b[s[x] + length - 1] == b[s[y] + length - 1]
    ahead = np.arange(length)

    def compare(pairs: np.ndarray) -> None:
        for i in range(0, len(pairs), 4096):
            own = pairs[i : i + 4096]
            equal[own] = (b[s[x[own]][:, None] + ahead] == b[s[y[own]][:, None] + ahead]).all(axis=1)

    compare(np.flatnonzero(~follows))
    if not equal.all():
        compare(np.arange(len(x)))  # what follows an unequal pair was taken on its word
    again, first = np.zeros(len(name), bool), np.ones(len(name), bool)
    again[x[equal]] = again[y[equal]] = True
    first[y[equal]] = False
    if not equal.all():
        for odd in np.unique(name[x[~equal]]):
            own, seen = np.flatnonzero(name == odd), {}
            again[own], first[own] = False, True
            for i in own:
                other = seen.setdefault(b[s[i] : s[i] + length].tobytes(), i)
                if other != i:
                    again[[i, other]], first[i] = True, False
    return again, first


def _as_stretches(piece: np.ndarray, within: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(piece, lo, hi) of stretches of starts, sorted by piece; they don't run on from one piece into the next."""
    place = piece.astype(np.int64) * np.int64(2) ** 32 + within
    new = np.flatnonzero(np.diff(place, prepend=-2) != 1)
    last = place[np.append(new[1:], len(place)) - 1] if len(place) else place
    return (place[new] >> 32), (place[new] & 0xFFFFFFFF).astype(np.int32), ((last & 0xFFFFFFFF) + 1).astype(np.int32)


#: Columns of what a part of a full bucket passes on: strings (digests of 16 bytes) of one source for one bucket of the second round.
PASSED = "bucket int, source binary, strings binary, owners array<binary>, counts array<int>, places binary"
FOUND = "digest binary, lo int, hi int, " + PASSED
PASSED_KINDS = (pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.binary()), pa.list_(pa.int32()), pa.binary())


def _names(schema: str) -> list[str]:
    return [x.split(" ")[0] for x in schema.split(", ")]


def _repeated_strings(length: int):
    def run(group: pa.Table) -> pa.Table:
        """digest, lo, hi: stretches of starts whose string also starts elsewhere in the group. A group that is a part of a full bucket also passes on the first start of each string, in rows for the buckets of a second round."""
        pieces = group.column("bytes").combine_chunks()
        digests = group.column("digest").combine_chunks()
        name, piece, within, s, b = _strings(pieces, length)
        again, first = _equal_neighbours(name, s, b, length)
        owner, lo, hi = _as_stretches(piece[again], within[again])
        hits = {"digest": digests.take(pa.array(owner)), "lo": pa.array(lo), "hi": pa.array(hi)}
        out = [pa.table(hits | {c: pa.nulls(len(lo), k) for c, k in zip(_names(PASSED), PASSED_KINDS, strict=True)})]
        if group.column("parts")[0].as_py() > 1:
            buckets = group.column("buckets")[0].as_py()
            one = np.flatnonzero(first)
            raw, source = b.tobytes(), digests[0].as_py()
            strings = np.frombuffer(b"".join(hashlib.blake2b(raw[i : i + length], digest_size=16).digest() for i in s[one].tolist()), "V16")
            bucket = (strings.view("<u8")[::2] % U(buckets)).astype(np.int64)
            rows = []
            for k in np.unique(bucket):
                own = np.flatnonzero(bucket == k)
                who, counts = np.unique(piece[one[own]], return_counts=True)  # starts are in the order of pieces
                rows.append((int(k), source, strings[own].tobytes(), digests.take(pa.array(who)).to_pylist(), counts.tolist(), within[one[own]].astype("<i4").tobytes()))
            columns = list(zip(*rows, strict=True)) or [()] * 6
            passed = {c: pa.array(x, k) for c, x, k in zip(_names(PASSED), columns, PASSED_KINDS, strict=True)}
            out.append(pa.table({"digest": pa.nulls(len(rows), pa.binary()), "lo": pa.nulls(len(rows), pa.int32()), "hi": pa.nulls(len(rows), pa.int32())} | passed))
        return pa.concat_tables(out)

    return run


def _met_again(group: pa.Table) -> pa.Table:
    """Of each row of a bucket of the second round, the starts whose string another source has too."""
    strings = np.concatenate([np.frombuffer(x.as_buffer(), "V16") for x in group.column("strings")])
    _, which, times = np.unique(strings, return_inverse=True, return_counts=True)
    again, at, out = times[which] > 1, 0, []
    for source, owners, counts, places in zip(*(group.column(c) for c in ("source", "owners", "counts", "places")), strict=True):
        counts = np.asarray(counts.values)
        hit = again[at : at + int(counts.sum())]
        at += len(hit)
        if hit.any():
            of = np.add.reduceat(hit.astype(np.int32), np.concatenate([[0], np.cumsum(counts)[:-1]]))
            has = np.flatnonzero(of)
            out.append((source.as_py(), owners.values.take(pa.array(has)).to_pylist(), of[has].tolist(), np.frombuffer(places.as_buffer(), "<i4")[hit].tobytes()))
    columns = list(zip(*out, strict=True)) or [()] * 4
    return pa.table({c: pa.array(x, k) for c, x, k in zip(("source", "owners", "counts", "places"), columns, (pa.binary(), *PASSED_KINDS[3:]), strict=True)})


def _merged(group: pa.Table) -> pa.Table:
    """digest, lo, hi: the starts of one source as stretches."""
    owners = pa.concat_arrays([x.values for x in group.column("owners")])
    names, who = np.unique(np.frombuffer(b"".join(owners.to_pylist()), f"V{len(owners[0].as_py())}"), return_inverse=True)
    owner = np.repeat(who, _numbers(group.column("counts")))
    place = np.concatenate([np.frombuffer(x.as_buffer(), "<i4") for x in group.column("places")])
    order = np.lexsort((place, owner))
    piece, lo, hi = _as_stretches(owner[order], place[order])
    return pa.table({"digest": pa.array([names[i].tobytes() for i in piece], pa.binary()), "lo": pa.array(lo), "hi": pa.array(hi)})


def repeated_starts(texts: DataFrame, total: int, length: int) -> DataFrame | None:
    """k, lo, hi: stretches of starts of repeated strings in texts (k, text), which are all different and hold `total` bytes."""
    period, residues = difference_cover(length)
    least_buckets = int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    buckets = max(least_buckets, -(-total * len(residues) // period // PER_BUCKET))
    named = sampled_names(texts, length, buckets)
    repeated = named.groupBy("bucket").applyInArrow(_repeated_names, REPEATED)
    stretches = written(repeated.groupBy("chunk").applyInArrow(_stretches(period), "k binary, lo array<int>, hi array<int>"), "starts-to-check")
    if stretches.isEmpty():
        return None
    runs = runs_of_starts(texts.join(small(stretches), "k"), length)
    runs = written(runs.select("least", "k", "at", F.unhex(F.sha2("bytes", 256)).alias("digest"), (F.octet_length("bytes") - (length - 1)).alias("n"), "bytes"), "runs-of-starts")
    # equal runs are repeated as a whole; one of each stands for all in what follows
    kinds = written(runs.groupBy("digest").agg(F.count("*").alias("times"), F.first("least").alias("least"), F.first("n").alias("n"), F.first("bytes").alias("bytes")), "distinct-runs")
    whole = kinds.where("times > 1").select("digest", F.lit(0).alias("lo"), F.col("n").cast("int").alias("hi"))
    # runs are compared with runs of the same least 8-gram, and with themselves, since a text may repeat itself
    starts = kinds.agg(F.sum("n")).first()[0]
    buckets = max(least_buckets, -(-starts // PER_BUCKET))
    dealt = kinds.withColumn("bucket", F.pmod(F.xxhash64("least"), F.lit(buckets)).cast("int"))
    loads = dealt.groupBy("bucket").agg(F.ceil(F.sum("n") / PER_BUCKET).cast("int").alias("parts"))
    full = written(loads.where("parts > 4"), "full-buckets")
    rounds = full.agg(F.coalesce(F.sum("parts"), F.lit(1)).cast("int")).first()[0]
    parts = F.coalesce("parts", F.lit(1))
    dealt = dealt.join(small(full), "bucket", "left").select("bucket", parts.alias("parts"), F.pmod(F.xxhash64("digest"), parts).cast("int").alias("part"), F.lit(rounds).alias("buckets"), "digest", "bytes")
    found = written(dealt.groupBy("bucket", "part").applyInArrow(_repeated_strings(length), FOUND), "repeated-strings")
    hits = found.where("lo is not null").select("digest", "lo", "hi")
    if rounds > 1:
        # strings of the parts of full buckets are met by digests of 128 bits (BLAKE2b); a string comes once from each part
        met = found.where("strings is not null").select(*_names(PASSED)).groupBy("bucket").applyInArrow(_met_again, "source binary, owners array<binary>, counts array<int>, places binary")
        hits = hits.unionByName(met.groupBy("source").applyInArrow(_merged, "digest binary, lo int, hi int"))
    hit = written(whole.unionByName(hits), "repeated-runs")
    return runs.select("k", "at", "digest").join(small(hit), "digest").select("k", (F.col("at") + F.col("lo")).alias("lo"), (F.col("at") + F.col("hi")).alias("hi"))


def removals(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (the bytes left) for each row of docs (doc_id, text).

    A null text is empty. A text that occurs twice or more is removed whole if it has `length` bytes. Texts below that
    keep all.
    """
    key = F.unhex(F.md5(F.col("text").cast("binary")))
    rows = docs.select("doc_id", text_or_empty().alias("text"))
    rows = rows.select("doc_id", "text", key.alias("k"))
    long = F.octet_length("text") >= length
    sizes = rows.where(long).select("k", F.octet_length("text").alias("n")).groupBy("k").agg(F.count("*").alias("times"), F.first("n").alias("n"))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    copied = written(sizes.where("times > 1").select("k"), "copied-texts")
    one_each = written(rows.where(long).join(small(copied), "k", "left_semi").groupBy("k").agg(F.first("text").alias("text")), "one-of-each")
    texts = rows.where(long).join(small(copied), "k", "left_anti").select("k", "text").unionByName(one_each)
    found = repeated_starts(texts, total, length) if total else None
    all_of = copied.select("k", F.lit(True).alias("whole"), F.lit(None).cast("array<struct<lo:int,hi:int>>").alias("starts"))
    if found is not None:
        stretches = found.join(small(copied), "k", "left_anti").groupBy("k").agg(F.array_sort(F.collect_set(F.struct("lo", "hi"))).alias("starts"))
        all_of = all_of.unionByName(stretches.select("k", F.lit(False).alias("whole"), "starts"))
    joined = rows.join(small(written(all_of, "removals")), "k", "left").select("doc_id", "text", "whole", "starts")
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text, whole, starts in zip(*(batch.column(i) for i in (1, 2, 3)), strict=True):
                b = text.as_buffer().to_pybytes()
                kept, removed, spans = [], 0, 0
                if whole.as_py():
                    removed, spans = len(b), 1
                else:
                    end = 0  # of what is decided so far
                    for x in starts.as_py() or ():
                        lo, hi = x["lo"], x["hi"] - 1 + length
                        if lo > end or not spans:
                            kept.append(b[end:lo])
                            spans += 1
                            removed += hi - lo
                            end = hi
                        elif hi > end:
                            removed += hi - end
                            end = hi
                    kept.append(b[end:])
                left = b"".join(kept)
                out.append((len(b), removed, spans, hashlib.sha256(left).hexdigest(), left))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            columns = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=[x.split(" ")[0] for x in schema.split(", ")])

    return joined.mapInArrow(run, schema)


def op10_difference_cover_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every document when strings of 400 bytes that also start elsewhere are gone."""
    return removals(table(spark, sf_dir, "documents")).drop("kept")
