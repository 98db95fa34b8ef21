"""Near-duplicate documents by probability-weighted MinHash.

A document is the set of its five-word shingles, weighted by 1 + ln(occurrences). Each shingle is a Poisson process of
that rate; an arrival falls on a random register, and a register keeps its earliest arrival. A shingle stops as soon as
its next arrival is later than everything its document's registers hold. Two registers agree with the probability
Jaccard similarity of the weighted sets. Bands of registers, drawn with these weights and with weights of 1, propose
pairs; a pair is a link if the exact Jaccard similarity of the two shingle sets reaches the threshold. Equal texts are
one node throughout.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkernel as K
from .components import linked, verified_by_sets
from .shared import small, table, text_or_empty, written

SHINGLE, THRESHOLD = 5, 0.8
BANDS, ROWS = 20, 4
U = np.uint64


def shingles(texts: pa.Array, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hash, text number) of all runs of `size` words, in order; a text of fewer words, but not none, is one shingle."""
    b, starts = K.joined(texts)
    at, end, lower = K.words(b)
    word = K.mixed(K.stretch_hashes(K.prefix_sums(lower), at, end))
    doc = np.searchsorted(starts, at, side="right") - 1
    n = len(word)
    if n == 0:
        return word, doc
    powers = K.POWERS.upto(size)[0]
    run = np.zeros(max(0, n - size + 1), U)
    for i in range(size):
        run += word[i : n - size + 1 + i] * powers[i]
    inside = doc[: len(run)] == doc[size - 1 :] if len(run) else np.zeros(0, bool)
    h, d = K.mixed(run[inside]), doc[: len(run)][inside]
    count = np.bincount(doc, minlength=len(texts))
    few = np.flatnonzero((count > 0) & (count < size))
    if len(few):
        first = np.searchsorted(doc, few)
        short = np.array([np.add.reduce(word[f : f + count[t]] * powers[: count[t]]) + U(count[t]) for f, t in zip(first, few, strict=True)], U)
        h, d = np.concatenate([h, K.mixed(short)]), np.concatenate([d, few])
        order = np.argsort(d, kind="stable")
        h, d = h[order], d[order]
    return h, d


def distinct_in_text(h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, text number, occurrences), sorted by text and hash."""
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    first = np.ones(len(h), bool)
    first[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    at = np.flatnonzero(first)
    return h[at], doc[at], np.diff(np.append(at, len(h)))


def registers(h: np.ndarray, doc: np.ndarray, weight: np.ndarray, texts: int, m: int) -> np.ndarray:
    """texts x m elements of the earliest arrivals, which agree where weights differ too; texts without elements keep zeros."""
    reg = np.full((texts, m), np.inf)
    flat = reg.reshape(-1)
    winner = np.zeros(texts * m, U)
    time = np.zeros(len(h))
    latest = np.full(texts, np.inf)
    step = 0
    while len(h):
        step += 1
        draw = K.mixed(h + U(step * 2 * K.BASE % (1 << 64)))
        time = time - np.log(((draw >> U(11)).astype(np.float64) + 1) * 2.0**-53) / weight
        cell = doc * m + (K.mixed(draw) % U(m)).astype(np.int64)
        np.minimum.at(flat, cell, time)
        won = time == flat[cell]
        winner[cell[won]] = h[won]
        touched = np.unique(doc)
        latest[touched] = reg[touched].max(axis=1)
        go = time < latest[doc]
        h, doc, weight, time = h[go], doc[go], weight[go], time[go]
    return winner.reshape(texts, m)


def band_keys(reg: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """texts x bands hashes of `rows` registers each, different from band to band."""
    bits = K.mixed(reg + U(1)).reshape(len(reg), bands, rows)
    powers = K.POWERS.upto(rows)[0]
    key = np.zeros((len(reg), bands), U)
    for i in range(rows):
        key += bits[:, :, i] * powers[i]
    return K.mixed(key + np.arange(bands, dtype=U)[None, :] * U(K.BASE))


def _over_texts(frame: DataFrame, schema: str, function) -> DataFrame:
    """mapInArrow over (node, text) in slices of bounded bytes; function(texts) gives a list array or null for each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, n in K.parts(batch.column(1)):
                part = batch.slice(at, n)
                yield pa.RecordBatch.from_arrays([part.column(0), function(part.column(1))], names=["node", "values"])

    return frame.select("node", "text").mapInArrow(run, schema)


def _lists(values: np.ndarray, counts: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(values.view(np.int64)))


def signatures(frame: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """node, values (band keys) of node, text; no keys for a text without words.

    A text that repeats a shingle also has the keys of its shingles at weight 1, which for other texts are the same keys.
    So any two texts share registers with the Jaccard similarity of their sets at least, whatever one of them repeats.
    """

    def make(texts: pa.Array) -> pa.ListArray:
        h, doc, n = distinct_in_text(*shingles(texts))
        keys = band_keys(registers(h, doc, 1 + np.log(n), len(texts), bands * rows), bands, rows)
        has = np.bincount(doc, minlength=len(texts)) > 0
        repeats = np.bincount(doc[n > 1], minlength=len(texts)) > 0
        of_repeats = repeats[doc]
        place = (np.cumsum(repeats) - 1)[doc[of_repeats]]
        even = band_keys(registers(h[of_repeats], place, np.ones(len(place)), int(repeats.sum()), bands * rows), bands, rows)
        both = np.concatenate([keys, keys], axis=1)
        wanted = np.repeat(has[:, None], 2 * bands, axis=1)
        wanted[:, bands:] = False
        both[repeats, bands:] = even
        wanted[repeats, bands:] = even != keys[repeats]
        return _lists(both[wanted], wanted.sum(axis=1))

    return _over_texts(frame, "node long, values array<long>", make)


def shingle_sets(frame: DataFrame) -> DataFrame:
    """node, values: the distinct shingle hashes of each text."""

    def make(texts: pa.Array) -> pa.ListArray:
        h, doc, _ = distinct_in_text(*shingles(texts))
        return _lists(h, np.bincount(doc, minlength=len(texts)))

    return _over_texts(frame, "node long, values array<long>", make)


def distinct_texts(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(node, text of one row for each text; doc_id, node of each row whose text has copies elsewhere). node is the smallest doc_id of a text."""
    marked = docs.where("doc_id is not null").select("doc_id", text_or_empty().alias("text"))
    digest = F.md5(F.col("text").cast("binary"))
    sizes = marked.select("doc_id", digest.alias("_d"))
    groups = sizes.groupBy("_d").agg(F.min("doc_id").alias("node"), F.count("*").alias("n")).where("n > 1")
    groups = written(groups.select("_d", "node"), "equal-texts")
    copies = written(sizes.join(small(groups), "_d").select("doc_id", "node"), "copies")
    others = written(copies.where("doc_id <> node").select("doc_id").distinct(), "other-copies")
    single = marked.join(small(others), "doc_id", "left_anti").select(F.col("doc_id").alias("node"), "text")
    return single, copies


def classes(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, class_id of each row of docs (doc_id, text).

    class_id is the smallest doc_id of the class. Null and empty texts are equal texts. Texts without words are alike only
    if equal. A null doc_id has a null class. A doc_id with several texts joins their classes' smallest.
    """
    single, copies = distinct_texts(docs)
    keys = written(signatures(single, bands, rows).select(F.explode("values").alias("key"), "node"), "bands")

    roots = linked(keys, lambda ids: single.join(small(ids), "node", "left_semi"), shingle_sets, verified_by_sets(shingle_sets, threshold), threshold)
    roots = written(roots, "near-roots")
    of_copy = copies.join(small(roots), "node", "left").select("doc_id", F.coalesce("root", "node").alias("class_id"))
    of_rest = roots.select(F.col("node").alias("doc_id"), F.col("root").alias("class_id"))
    known = written(of_copy.unionByName(of_rest).groupBy("doc_id").agg(F.min("class_id").alias("class_id")), "near-classes")
    return docs.select("doc_id").join(small(known), "doc_id", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))


def op8_probminhash_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document, with the class of near duplicates that it belongs to."""
    found = classes(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "class_id", (F.col("doc_id") == F.col("class_id")).alias("kept"))


def keep_one_each(docs: DataFrame) -> DataFrame:
    """docs with one document of each class, that with the smallest doc_id; all columns stay. Rows without doc_id stay."""
    found = classes(docs.select("doc_id", "text"))
    gone = written(found.where("doc_id <> class_id").select("doc_id").distinct(), "near-copies")
    kept = docs.join(small(gone), "doc_id", "left_anti").select(*docs.columns)
    return kept.withColumn("_d", F.md5(text_or_empty().cast("binary"))).dropDuplicates(["doc_id", "_d"]).drop("_d")
