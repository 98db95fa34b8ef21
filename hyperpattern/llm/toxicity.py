"""Toxicity from the nearest labelled examples by exact TF-IDF cosine.

Terms are words and the 4- to 7-byte beginnings of longer words. The labelled sample, of at most EXAMPLES rows of each
label, gives the examples, with all their terms; document frequencies come from all documents, and terms tied to
label 1 weigh EMPHASIS times as much as their TF-IDF, the others as it is; none is dropped. The examples are an
inverted index in blocks of similar examples, with each common term's largest weight in a block. A document's rare terms
add their postings; its common terms are multiplied only in blocks whose bound reaches the best cosines found so far.
All examples that rounding leaves near the last place are weighed again in double precision, so the neighbours are exact
and every text that shares a term with an example has some. Their votes, weighted by cosine and by
how the labels were sampled, are calibrated on the examples themselves, each scored without itself, by pooling adjacent
violators.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import let_go, small, table, text_or_empty, written

#: Bound of the fitted part: labelled rows of each label.
EXAMPLES = 8000
NEIGHBOURS, PRIOR_WEIGHT = 16, 0.25
PREFIXES = (4, 5, 6, 7)
#: A term is tied to label 1 by chi-square, rows with label 1 (and their share), and how many times commoner there; such a term weighs EMPHASIS times its TF-IDF.
CHI_SQUARE, LEAST_ROWS, LEAST_SHARE, RATIO, EMPHASIS = 20.0, 4, 1 / 250, 5, 4.0
#: Terms that more than one in COMMON examples have, at most DENSE of them, are dense rows. Texts are searched ROWS at a time. ROUNDING: more than single precision can be off in a cosine.
COMMON, DENSE, ROWS, ROUNDING = 64, 1024, 128, 1e-5
#: Examples in a block of the index. Slices, a power of two, in which the examples' vectors come to the driver. Postings of rare terms that are summed at once, so that they stay in the cache.
BLOCK, SLICES, POSTINGS = 64, 16, 1 << 15


def terms(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(term hash, text number) of all term occurrences; the toolkit's hashes of bytes, salted by the kind of term."""
    b, starts = K.joined(texts)
    at, end, lower = K.words(b)
    sums = K.prefix_sums(lower)
    found, at_text = [K.mixed(K.stretch_hashes(sums, at, end))], [np.searchsorted(starts, at, side="right") - 1]
    for n in PREFIXES:
        long = end - at > n
        found.append(K.mixed(K.stretch_hashes(sums, at[long], at[long] + n) + np.uint64(n)))
        at_text.append(at_text[0][long])
    return np.concatenate(found), np.concatenate(at_text)


class Lookup:
    """Numbers of known hashes; the first bits of a hash give the place where its likes begin."""

    def __init__(self, sorted_hashes: np.ndarray):
        self.known = sorted_hashes
        bits = max(1, len(sorted_hashes).bit_length())
        self.shift = np.uint64(64 - bits)
        n = np.bincount((sorted_hashes >> self.shift).astype(np.int64), minlength=1 << bits)
        self.first = np.concatenate([[0], np.cumsum(n)])
        self.most = int(n.max())

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places in hashes, numbers), by place."""
        number = np.full(len(hashes), -1, np.int64)
        left = np.arange(len(hashes))
        bucket = (hashes >> self.shift).astype(np.int64)
        at, end = self.first[bucket], self.first[bucket + 1]
        for _ in range(self.most):
            more = at < end
            left, at, end = left[more], at[more], end[more]
            same = self.known[at] == hashes[left]
            number[left[same]] = at[same]
            left, at, end = left[~same], at[~same] + 1, end[~same]
        place = np.flatnonzero(number >= 0)
        return place, number[place]


def term_counts(texts: pa.Array, lookup: Lookup) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text number, term number, occurrences), sorted."""
    h, doc = terms(texts)
    place, number = lookup.find(h)
    pair, n = np.unique(doc[place] * np.int64(len(lookup.known) + 1) + number, return_counts=True)
    return pair // (len(lookup.known) + 1), pair % (len(lookup.known) + 1), n


def weights(doc: np.ndarray, term: np.ndarray, n: np.ndarray, idf: np.ndarray, texts: int) -> np.ndarray:
    """TF-IDF of unit length for each text."""
    w = (1 + np.log(n)) * idf[term]
    return w / np.sqrt(np.bincount(doc, w * w, texts))[doc]


@dataclass
class InvertedIndex:
    """All terms of all examples: by example (start, own_term, own_weight), which is what travels, and by term (common terms dense, rare ones as postings), which each process that searches makes of it."""

    start: np.ndarray  # of an example into own_term
    own_term: np.ndarray
    own_weight: np.ndarray
    label: np.ndarray
    vote: np.ndarray  # of an example, by how its label was sampled
    name: np.ndarray
    n_terms: int

    # all postings, for those who look into an index; a search holds the rare terms' only
    @property
    def pointer(self) -> np.ndarray:
        return np.concatenate([[0], np.cumsum(np.bincount(self.own_term, minlength=self.n_terms))])

    @property
    def example(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.label)), np.diff(self.start))[np.argsort(self.own_term, kind="stable")]

    @property
    def weight(self) -> np.ndarray:
        return self.own_weight[np.argsort(self.own_term, kind="stable")]

    def of(self, e: int) -> tuple[np.ndarray, np.ndarray]:
        own = slice(self.start[e], self.start[e + 1])
        return self.own_term[own], self.own_weight[own]

    def __reduce__(self):
        return InvertedIndex, (self.start, self.own_term, self.own_weight, self.label, self.vote, self.name, self.n_terms)

    def forms(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Made once in a process that searches: (row of a common term or -1, place of an example, example at a place, weights by block, common term and place in it, largest weights by common term and block, where a rare term's postings begin, their places and weights)."""
        if not hasattr(self, "_forms"):
            n, lengths = len(self.label), np.zeros(self.n_terms, np.int64)
            for at in range(0, len(self.own_term), 1 << 20):
                lengths += np.bincount(self.own_term[at : at + (1 << 20)], minlength=self.n_terms)
            common = np.argsort(-lengths, kind="stable")[:DENSE]
            common = common[lengths[common] > n / COMMON]
            row = np.full(len(lengths), -1, np.int32)
            row[common] = np.arange(len(common))
            order = self._alike(lengths)
            place = np.empty(n, np.int32)
            place[order] = np.arange(n)
            dense = np.zeros((-(-n // BLOCK), len(common), BLOCK), np.float32)
            lengths[common] = 0
            pointer = np.concatenate([[0], np.cumsum(lengths)])
            at_place = np.empty(pointer[-1], np.uint16 if n <= 1 << 16 else np.int32)
            weight = np.empty(pointer[-1], np.float32)
            to = pointer[:-1].copy()
            for e in range(n):  # no example has a term twice; sorting the postings would take several times their size
                t, w = self.of(e)
                rare = row[t] < 0
                dense[place[e] // BLOCK, row[t[~rare]], place[e] % BLOCK] = w[~rare]
                t = t[rare]
                at_place[to[t]], weight[to[t]] = place[e], w[rare]
                to[t] += 1
            self._forms = row, place, order, dense, np.ascontiguousarray(dense.max(axis=2).T), pointer, at_place, weight
        return self._forms

    def _rare(self, term: np.ndarray, weight: np.ndarray, n: int, room: list[np.ndarray]) -> np.ndarray:
        """Sums of a text's rare terms by place. Postings are copied into the same room, a cache full at a time, since fresh pages cost more than the sums."""
        *_, pointer, at_place, own = self.forms()
        out = np.zeros(n)
        first, last = pointer[term], pointer[term + 1]
        lengths = last - first
        so_far = np.cumsum(lengths)
        first, last = first.tolist(), last.tolist()
        a = 0
        while a < len(term):
            before = so_far[a] - lengths[a]
            b = max(a + 1, int(np.searchsorted(so_far, before + POSTINGS, side="right")))
            m = int(so_far[b - 1] - before)
            if m > len(room[0]):
                room[:] = np.empty(m, np.int64), np.empty(m)
            to, w = room[0][:m], room[1][:m]
            spans = [slice(x, y) for x, y in zip(first[a:b], last[a:b], strict=True)]
            np.concatenate([at_place[x] for x in spans], out=to)
            np.concatenate([own[x] for x in spans], out=w)
            w *= np.repeat(weight[a:b], lengths[a:b])
            out += np.bincount(to, w, n)
            a = b
        return out

    def _alike(self, lengths: np.ndarray) -> np.ndarray:
        """The examples, ordered by the numbers of their three heaviest terms among those neither rare nor in most examples, so that blocks hold similar ones."""
        n = len(self.label)
        fit = (lengths * COMMON >= n) & (lengths * 3 <= n) & (lengths > 1)
        heavy = np.full((3, n), -1)
        for e in range(n):
            t, w = self.of(e)
            t, w = t[fit[t]], w[fit[t]]
            first = np.argsort(-w, kind="stable")[:3]
            heavy[: len(first), e] = t[first]
        return np.lexsort(heavy[::-1])

    def search(self, doc: np.ndarray, term: np.ndarray, weight: np.ndarray, k: int = NEIGHBOURS, skip: np.ndarray | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(text, examples, cosines) of each text of the sorted triples: the k nearest with a cosine over 0, nearest first; ties go to the lower example. skip: an example to leave out for each text.

        A block's bound is its largest sum of rare terms' postings, and the common terms' largest weights in it. The blocks
        with the highest bounds give a cosine that k examples reach; common terms are multiplied in blocks that may reach it.
        """
        row, place, order, dense, top, *_ = self.forms()
        blocks = len(dense)
        n = blocks * BLOCK  # places
        ahead = min(blocks, -(-2 * k // BLOCK))
        query, asked, room = np.zeros(len(row)), np.zeros(len(row), bool), [np.empty(POSTINGS, np.int64), np.empty(POSTINGS)]
        edge = np.flatnonzero(np.diff(doc, prepend=-1, append=-2))
        for first in range(0, len(edge) - 1, ROWS):
            last = min(first + ROWS, len(edge) - 1)
            lo, hi = edge[first], edge[last]
            at = np.repeat(np.arange(last - first), np.diff(edge[first : last + 1]))
            own = row[term[lo:hi]]
            left = np.zeros((last - first, len(top)), np.float32)
            left[at[own >= 0], own[own >= 0]] = weight[lo:hi][own >= 0]
            score = np.empty((last - first, n), np.float32)
            for i in range(last - first):
                t, w = term[edge[first + i] : edge[first + i + 1]], weight[edge[first + i] : edge[first + i + 1]]
                rare = row[t] < 0
                score[i] = self._rare(t[rare], w[rare], n, room)
            texts = doc[edge[first:last]]
            every = np.arange(last - first)
            if skip is not None:
                score[every, place[skip[texts]]] = -np.inf
            of_block = score.reshape(last - first, blocks, BLOCK)
            bound = left @ top + of_block.max(axis=2)
            best = np.argpartition(-bound, ahead - 1, axis=1)[:, :ahead]
            done = np.zeros(bound.shape, bool)
            done[every[:, None], best] = True
            self._multiply(of_block, left, done)
            sure = of_block[every[:, None], best].reshape(last - first, -1)
            reached = np.partition(sure, -k, axis=1)[:, -k] if sure.shape[1] >= k else np.zeros(last - first)
            self._multiply(of_block, left, (bound > 0) & (bound >= reached[:, None] - 2 * ROUNDING) & ~done)
            least = np.partition(score, n - k, axis=1)[:, n - k] - ROUNDING if n > k else np.zeros(last - first)
            near, found = np.nonzero((score >= least[:, None]) & (score > 0))
            limits = np.searchsorted(near, np.arange(last - first + 1))
            for i in range(last - first):
                e = order[found[limits[i] : limits[i + 1]]]
                a, b = edge[first + i], edge[first + i + 1]
                query[term[a:b]], asked[term[a:b]] = weight[a:b], True
                s = self._cosines(e, query, asked)
                asked[term[a:b]] = False
                by_rank = np.lexsort((e, -s))[:k]
                yield int(texts[i]), e[by_rank], s[by_rank]

    def _cosines(self, e: np.ndarray, query: np.ndarray, asked: np.ndarray) -> np.ndarray:
        """Of the examples e with a text, in double precision. asked: which terms the text has, a table that stays in the cache where query doesn't."""
        if not len(e):
            return np.zeros(0)
        spans = [slice(x, y) for x, y in zip(self.start[e].tolist(), self.start[e + 1].tolist(), strict=True)]
        own = np.concatenate([self.own_term[x] for x in spans])
        hit = np.flatnonzero(asked.take(own))
        parts = query.take(own[hit]) * np.concatenate([self.own_weight[x] for x in spans])[hit]
        which = np.repeat(np.arange(len(e)), self.start[e + 1] - self.start[e])[hit]
        return np.bincount(which, parts, len(e))

    def _multiply(self, of_block: np.ndarray, left: np.ndarray, wanted: np.ndarray) -> None:
        """Adds the common terms' part where it is wanted, block by block."""
        dense = self.forms()[3]
        for b in np.flatnonzero(wanted.any(axis=0)):
            who = np.flatnonzero(wanted[:, b])
            of_block[who, b] += left[who] @ dense[b]

    def nearest(self, term: np.ndarray, weight: np.ndarray, k: int = NEIGHBOURS, skip: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """(examples, cosines) of one text."""
        found = self.search(np.zeros(len(term), np.int64), term, weight, k, None if skip < 0 else np.array([skip]))
        return next(((e, s) for _, e, s in found), (np.zeros(0, np.int64), np.zeros(0)))


@dataclass
class Model:
    hashes: np.ndarray
    idf: np.ndarray  # with the emphasis
    index: InvertedIndex | None
    base: float  # share of label 1 among rows without terms
    bounds: np.ndarray
    values: np.ndarray
    sent = None  # the broadcast model, before its calibration

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "sent"}

    def vote(self, e: np.ndarray, s: np.ndarray) -> float:
        w = s * self.index.vote[e]
        return float((w @ self.index.label[e] + PRIOR_WEIGHT * self.base) / (w.sum() + PRIOR_WEIGHT))

    def calibrated(self, vote: float) -> float:
        return float(np.interp(vote, self.bounds, self.values)) if len(self.bounds) else vote

    def score(self, texts: pa.Array) -> tuple[np.ndarray, list[list[tuple[int, float, int]]]]:
        """Scores, and the three nearest examples of each text as (hash of its text, cosine, label)."""
        out, evidence = np.full(len(texts), self.base), [[] for _ in range(len(texts))]
        if self.index is None:
            return out, evidence
        doc, term, n = term_counts(texts, Lookup(self.hashes))
        w = weights(doc, term, n, self.idf, len(texts))
        for i, e, s in self.index.search(doc, term, w):
            if len(e):
                out[i] = self.calibrated(self.vote(e, s))
                evidence[i] = [(int(self.index.name[x]), float(y), int(self.index.label[x])) for x, y in zip(e[:3], s[:3], strict=True)]
        return out, evidence


def pooled(votes: np.ndarray, labels: np.ndarray, mass: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Isotonic calibration: (votes, rates) at the middles of the pooled groups."""
    groups: list[list[float]] = []
    for v, y, m in sorted(zip(votes, labels, mass, strict=True)):
        groups.append([v * m, y * m, m])
        while len(groups) > 1 and groups[-2][1] / groups[-2][2] >= groups[-1][1] / groups[-1][2]:
            last = groups.pop()
            groups[-1] = [a + b for a, b in zip(groups[-1], last, strict=True)]
    g = np.array(groups)
    return g[:, 0] / g[:, 2], g[:, 1] / g[:, 2]


def _batched(function, frame: DataFrame, columns: list[str], schema: str) -> DataFrame:
    """mapInArrow in slices of bounded bytes; function(slice) gives the arrays of a batch. The text is the last column."""
    names = [x.strip().split(" ")[0] for x in schema.split(", ")] if "<" not in schema else [x.split(" ")[0] for x in schema.split(", ") if " " in x and "<" not in x.split(" ")[0]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, n in K.parts(batch.column(batch.num_columns - 1)):
                yield pa.RecordBatch.from_arrays(function(batch.slice(at, n)), names=names)

    return frame.select(*columns).mapInArrow(run, schema)


def learnable(labels: DataFrame) -> DataFrame:
    """doc_id, toxic of the rows that may be learned from: crc32 of the id as text isn't a multiple of 5."""
    rest = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5
    return labels.where((rest != 0) & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))


def _collected(df: DataFrame) -> pa.Table:
    """df on the driver, which has first let go of what earlier jobs left there."""
    let_go(df.sparkSession)
    return df.toArrow()


def _tied(counted: pa.Table, n: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """(sorted hashes, which are tied to label 1) of counts by term and label. n: examples of each label. Its tables end with it, so that they aren't held beside the vectors."""
    hashes = counted.column("term").to_numpy().view(np.uint64)
    order = np.argsort(hashes)
    a, b = (counted.column(x).to_numpy().astype(float)[order] for x in ("pos", "neg"))
    chi = (n[0] + n[1]) * (a * (n[0] - b) - b * (n[1] - a)) ** 2 / ((a + b) * (n[1] - a + n[0] - b) * float(n[1]) * float(n[0]) + 1e-9)
    return hashes[order], (a / n[1] > RATIO * b / n[0]) & (a >= max(LEAST_ROWS, n[1] * LEAST_SHARE)) & (chi >= CHI_SQUARE)


def _idf(counted: pa.Table, rows: int, tied: np.ndarray) -> np.ndarray:
    df = np.zeros(len(tied))
    df[counted.column("term").to_numpy()] = counted.column("n").to_numpy()
    return (np.log((1 + rows) / (1 + df)) + 1) * np.where(tied, EMPHASIS, 1.0)


def fit(docs: DataFrame, labels: DataFrame, examples: int = EXAMPLES) -> Model:
    """A model of bounded many examples from docs (doc_id, text) and labels (doc_id, toxic). Without labelled rows all scores are 0."""
    allowed = written(learnable(labels), "learnable")
    text = text_or_empty()
    labelled = docs.join(small(allowed), "doc_id").select(F.xxhash64(text).alias("name"), "toxic", text.alias("text"))
    names = written(labelled.select("name", "toxic"), "labelled")
    cut, have = {}, {}
    for y in (0, 1):
        of = names.where(F.col("toxic") == y)
        have[y] = of.count()
        last = of.orderBy("name").limit(examples).agg(F.max("name")).first()[0]
        cut[y] = -(1 << 63) if last is None else last
    sample = written(labelled.where(F.col("name") <= F.when(F.col("toxic") == 1, cut[1]).otherwise(cut[0])), "examples")
    n = {y: sample.where(F.col("toxic") == y).count() for y in (0, 1)}
    empty = Model(np.zeros(0, np.uint64), np.zeros(0), None, 0.0, np.zeros(0), np.zeros(0))
    if not n[1] or not n[0]:
        empty.base = float(bool(n[1]))
        return empty

    def by_label(batch: pa.RecordBatch) -> list:
        h, doc = terms(batch.column(1))
        y = batch.column(0).to_numpy(zero_copy_only=False)
        order = np.lexsort((h, doc))
        h, doc = h[order], doc[order]
        first = np.ones(len(h), bool)
        first[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
        known, back = np.unique(h[first], return_inverse=True)
        pos = np.bincount(back, y[doc[first]], len(known)).astype(np.int64)
        return [pa.array(known.view(np.int64)), pa.array(pos), pa.array(np.bincount(back, minlength=len(known)).astype(np.int64) - pos)]

    distinct = sample.dropDuplicates(["name", "toxic"])  # copies of a text are one witness
    counted = _batched(by_label, distinct, ["toxic", "text"], "term long, pos long, neg long").groupBy("term").agg(F.sum("pos").cast("int").alias("pos"), F.sum("neg").cast("int").alias("neg"))  # all terms of at most 2 * examples texts
    hashes, tied = _tied(_collected(counted), n)
    if not len(hashes):
        empty.base = have[1] / (have[0] + have[1])
        return empty
    shared = docs.sparkSession.sparkContext.broadcast(hashes)

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lookup = Lookup(shared.value)
        n = np.zeros(len(lookup.known), np.int64)
        for batch in batches:
            for at, m in K.parts(batch.column(0)):
                n += np.bincount(term_counts(batch.column(0).slice(at, m), lookup)[1], minlength=len(n))
        seen = np.flatnonzero(n)
        for at in range(0, len(seen), 1 << 16):
            k = seen[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(n[k])], names=["term", "n"])

    every = docs.select(text.alias("text"))
    counted = every.mapInArrow(frequencies, "term long, n long").groupBy("term").agg(F.sum("n").alias("n"))
    idf = _idf(_collected(counted), docs.count(), tied)
    given = docs.sparkSession.sparkContext.broadcast(idf)

    def vectors(batch: pa.RecordBatch) -> list:
        doc, term, m = term_counts(batch.column(3), Lookup(shared.value))
        w = weights(doc, term, m, given.value, batch.num_rows)
        edge = np.searchsorted(doc, np.arange(batch.num_rows + 1)).astype(np.int32)
        lists = [pa.ListArray.from_arrays(pa.array(edge), pa.array(v)) for v in (term.astype(np.int32), w.astype(np.float32))]
        return [batch.column(0), batch.column(1), batch.column(2), *lists]

    def of_slice(i: int) -> pa.Table:
        """Copies of a text are one row before their vector is made, so vectors are not shuffled."""
        texts = sample.where(F.shiftright("name", 64 - SLICES.bit_length() + 1) == i).groupBy("name", "toxic").agg(F.count("*").alias("n"), F.first("text").alias("text"))
        return _collected(_batched(vectors, texts, ["name", "toxic", "n", "text"], "name long, toxic int, n long, term array<int>, weight array<float>")).sort_by([("name", "ascending"), ("toxic", "ascending")])

    model = _index(hashes, idf, of_slice, {y: have[y] / n[y] for y in n})  # at most 2 * examples
    return _calibrate(docs.sparkSession, model)


def _index(hashes: np.ndarray, idf: np.ndarray, of_slice: Callable[[int], pa.Table], rate: dict[int, float]) -> Model:
    """The examples arrive in slices of their hashes, in order, so that no process holds all rows at once beside their arrays."""
    parts, terms_of, weights_of = [], [], []
    for i in range(-SLICES // 2, SLICES // 2):
        part = of_slice(i)
        parts.append([part.column(c).to_numpy() for c in ("name", "toxic", "n")] + [pc.list_value_length(part.column("term")).to_numpy()])
        for held, c in ((terms_of, "term"), (weights_of, "weight")):
            held += [np.array(x.flatten().to_numpy()) for x in part.column(c).chunks]
    del part, held
    term, weight = _drained(terms_of, np.int32), _drained(weights_of, np.float32)
    pa.default_memory_pool().release_unused()
    name, label, copies, lengths = (np.concatenate(x) for x in zip(*parts, strict=True))
    mass = copies * np.where(label == 1, rate[1], rate[0])
    blank = lengths == 0
    of = blank if blank.any() else ~blank
    base = float(mass[of & (label == 1)].sum() / mass[of].sum())
    some = np.flatnonzero(~blank)
    start = np.concatenate([[0], np.cumsum(lengths[some])])
    index = InvertedIndex(start, term, weight, label[some].astype(float), mass[some] / min(rate.values()), name[some], len(hashes))
    return Model(hashes, idf, index, base, np.zeros(0), np.zeros(0))


def _drained(parts: list[np.ndarray], kind: type) -> np.ndarray:
    """The parts end to end; each is let go as soon as it is copied."""
    out = np.empty(sum(map(len, parts)), kind)
    end = len(out)
    while parts:
        part = parts.pop()
        out[end - len(part) : end] = part
        end -= len(part)
    return out


def _calibrate(spark: SparkSession, model: Model) -> Model:
    """Each example's vote without itself, taken by the executors, and the rates pooled from the votes. The model travels once, here."""
    model.sent = shared = spark.sparkContext.broadcast(model)
    n = len(model.index.label)

    def leave_one_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        start, own_term, own_weight = model.index.start, model.index.own_term, model.index.own_weight
        for batch in batches:
            ids = batch.column(0).to_numpy()
            votes = np.full(len(ids), model.base)
            for first in range(0, len(ids), 8 * ROWS):
                e = ids[first : first + 8 * ROWS]  # consecutive
                own = slice(start[e[0]], start[e[-1] + 1])
                at = np.repeat(np.arange(len(e)), np.diff(start[e[0] : e[-1] + 2]))
                for i, near, s in model.index.search(at, own_term[own], own_weight[own], skip=e):
                    if len(near):
                        votes[first + i] = model.vote(near, s)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(votes)], names=["id", "vote"])

    found = spark.range(0, n, 1, max(1, -(-n // (4 * ROWS)))).mapInArrow(leave_one_out, "id long, vote double").toArrow()
    votes = np.empty(n)
    votes[found.column("id").to_numpy()] = found.column("vote").to_numpy()
    model.bounds, model.values = pooled(votes, model.index.label, model.index.vote)
    return model


SCORED = "score double, evidence array<struct<example:long,cosine:double,toxic:int>>"


def score_texts(docs: DataFrame, model: Model, keep: list[str]) -> DataFrame:
    """The columns in keep with score (0 to 1) and evidence; null and empty texts, and texts that share no term with an example, get the rate of rows without terms."""
    spark = docs.sparkSession
    shared, bounds, values = model.sent or spark.sparkContext.broadcast(model), model.bounds, model.values
    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema)
    kind = pa.list_(pa.struct([("example", pa.int64()), ("cosine", pa.float64()), ("toxic", pa.int32())]))
    at = [*keep, "_scored_text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shared.value.bounds, shared.value.values = bounds, values
        for batch in batches:
            for first, n in K.parts(batch.column(len(keep))):
                part = batch.slice(first, n)
                score, evidence = shared.value.score(part.column(len(keep)))
                found = pa.array([[{"example": a, "cosine": c, "toxic": y} for a, c, y in x] for x in evidence], kind)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), pa.array(score), found], names=[*keep, "score", "evidence"])

    return docs.withColumn("_scored_text", F.col("text")).select(*at).mapInArrow(run, f"{kept}, {SCORED}")


def op4_toxicity_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored by its nearest labelled examples."""
    docs = table(spark, sf_dir, "documents")
    model = fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels"))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(True))
    return score_texts(docs, model, ["doc_id"]).select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "evidence")


def drop_toxic(docs: DataFrame, labels: DataFrame, at_least: float = 0.5) -> DataFrame:
    """docs without the rows that score `at_least`; all columns stay, whatever their names."""
    model = fit(docs.select("doc_id", "text"), labels)
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "text")
    return score_texts(packed, model, ["row"]).where(F.col("score") < at_least).select("row.*")
