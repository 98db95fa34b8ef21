"""Operators on documents against brute force on small tables with nulls, empty and long texts, ties, repeats and clashing columns."""

import collections
import hashlib
import random
import re
import sys
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from hyperpattern.llm import components as linking
from hyperpattern.llm import decontam, line_dedup, near_dup, packing, repeats, sharding, textkernel, toxicity
from hyperpattern.llm.components import components
from hyperpattern.llm.shared import written

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = str.maketrans(decontam.UPPER, decontam.LOWER)
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, node long, key string"


def words(text):
    return WORD.findall((text or "").translate(LOW))


def corpus(seed=0, n=60):
    r = random.Random(seed)
    vocabulary = ["".join(r.choice("abcdeé") for _ in range(r.randint(2, 7))) for _ in range(300)]
    sentence = lambda k: " ".join(r.choice(vocabulary) for _ in range(k))
    shared = sentence(120)
    texts = [sentence(r.choice((3, 40, 150))) + "\n" + sentence(20) for _ in range(n)]
    base = sentence(200)
    for i in range(8):
        w = base.split()
        w[10 * i] = "changed"
        texts.append(" ".join(w))
    texts += [base, base, base.upper(), None, "", "", "   \n\n", "one", "ÉÀ", "x" * 3000, "ab " * 2000, shared + " " + sentence(9), sentence(9) + " " + shared, "a\n" + shared + "\nb\nb"]
    return texts


@pytest.fixture(scope="module")
def texts():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", None, 1.0, 7, "k") for i, t in enumerate(texts)], SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_components(spark):
    r = random.Random(1)
    edges = [(r.randint(0, 60), r.randint(0, 60)) for _ in range(45)] + [(i, i + 1) for i in range(100, 140)]
    parent = {x: x for e in edges for x in e}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    got = {x["node"]: x["root"] for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: root(x) for e in edges if e[0] != e[1] for x in e}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def brute_lines(texts):
    where, sets = collections.defaultdict(list), {}
    for i, t in enumerate(texts):
        for k, line in enumerate((t or "").split("\n")):
            if re.search(r"[0-9A-Za-z\u0080-\U0010FFFF]", line):
                where[line].append((i, k))
                b = line.encode()
                sets[line] = {b[j : j + line_dedup.SHINGLE] for j in range(max(1, len(b) - line_dedup.SHINGLE + 1))}
    parent = {x: x for x in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                parent[root(b)] = root(a)
    groups = collections.defaultdict(list)
    for x in sets:
        groups[root(x)] += where[x]
    return {min(g) for g in groups.values()}, {p for ps in where.values() for p in ps}


def test_line_dedup(docs, none, texts):
    kept, judged = brute_lines(texts)
    got = line_dedup.judged_lines(docs.select("doc_id", "text")).collect()
    assert {(r["doc_id"], r["line_no"]) for r in got if r["kept"]} & judged == kept
    assert len(got) == sum(len((t or "").split("\n")) for t in texts)
    out = {r["doc_id"]: r for r in line_dedup.without_repeated_lines(docs).collect()}
    for i, t in enumerate(texts):
        lines = (t or "").split("\n")
        want = "\n".join(x for k, x in enumerate(lines) if (i, k) in kept or (i, k) not in judged)
        assert out[i]["text"] == (want if t is not None else None)
    assert line_dedup.without_repeated_lines(docs).columns == docs.columns
    assert line_dedup.judged_lines(none).count() == 0 and line_dedup.without_repeated_lines(none).count() == 0


def test_line_dedup_runs_no_python(docs):
    plan = line_dedup.judged_lines(docs.select("doc_id", "text"))._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_near_duplicates(docs, none, texts):
    s = {}
    for i, t in enumerate(texts):
        w = words(t)
        s[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else {("text", t or "")}
    parent = {i: i for i in s}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in s:
        for b in range(a):
            if len(s[a] & s[b]) >= 0.8 * len(s[a] | s[b]):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    got = {r["doc_id"]: r["class_id"] for r in near_dup.classes(docs.select("doc_id", "text")).collect()}
    assert got == {i: root(i) for i in s}
    kept = near_dup.keep_one_each(docs)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(i for i in s if root(i) == i) and kept.columns == docs.columns
    assert near_dup.classes(none).count() == 0


def test_registers_estimate_probability_jaccard():
    r = np.random.default_rng(3)
    ids = textkernel.mixed(np.arange(1, 401, dtype=np.uint64))
    w = r.uniform(0.5, 4, 400)
    a, b = np.arange(0, 300), np.arange(60, 400)
    wa, wb = w[a], w[b] * r.uniform(0.8, 1.2, len(b))
    m = 4096
    reg = near_dup.registers(np.concatenate([ids[a], ids[b]]), np.repeat([0, 1], [len(a), len(b)]), np.concatenate([wa, wb]), 2, m)
    x, y = dict(zip(a, wa, strict=True)), dict(zip(b, wb, strict=True))
    true = sum(1 / sum(max(x.get(j, 0) / x[i], y.get(j, 0) / y[i]) for j in {*x, *y}) for i in {*x} & {*y})
    assert abs((reg[0] == reg[1]).mean() - true) < 4 * (true * (1 - true) / m) ** 0.5


def test_a_text_that_repeats_itself_meets_its_near_copy(spark):
    r = random.Random(11)
    pairs = []
    for i in range(0, 120, 2):
        w = ["w%d" % r.randrange(10**6) for _ in range(200)]
        pairs += [(i, " ".join(w)), (i + 1, " ".join(w[:100] + ["x%d" % i] + w[100:] + w[:36] * 19))]
    got = {x["node"]: set(x["values"]) for x in near_dup.signatures(spark.createDataFrame(pairs, "node long, text string")).collect()}
    assert all(got[i] & got[i + 1] for i in range(0, 120, 2))
    assert all(len(got[i]) == near_dup.BANDS < len(got[i + 1]) for i in range(0, 120, 2))
    assert near_dup.classes(spark.createDataFrame(pairs, "doc_id long, text string")).where("class_id % 2 = 1").count() == 0


def test_null_ids_and_repeated_rows(spark):
    rows = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c d e f"), (2, None)], "doc_id long, text string")
    assert sorted(((r["doc_id"], r["class_id"]) for r in near_dup.classes(rows).collect()), key=str) == [(1, 1), (1, 1), (2, 2), (None, None)]
    assert near_dup.keep_one_each(rows).count() == 3
    assert decontam.contamination(rows, rows.select(F.col("doc_id").alias("item_id"), "text")).count() == 4


def test_decontamination(spark, docs, none, texts):
    items = [("a", " ".join((texts[0] + " " + texts[1]).split()[:30])), ("b", "One"), ("c", None), ("d", texts[60].split("\n")[0]), ("e", "ab ab ab"), ("a2", " ".join((texts[0] + " " + texts[1]).split()[5:20]))]
    bench = spark.createDataFrame(items, "item_id string, text string")
    windows = collections.defaultdict(set)
    for i, t in items:
        w = words(t)
        n = min(13, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows[tuple(w[k : k + n])].add(i)
    want = {}
    for d, t in enumerate(texts):
        w, hit, who = words(t), set(), set()
        for x, ids in windows.items():
            for k in range(len(w) - len(x) + 1):
                if tuple(w[k : k + len(x)]) == x:
                    hit.update(range(k, k + len(x)))
                    who |= ids
        want[d] = (len(w), len(hit), len(who), hashlib.sha256(",".join(sorted(who)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in decontam.contamination(docs, bench).collect()}
    assert got == want and any(x[4] for x in want.values())
    left = decontam.drop_contaminated(docs, bench)
    assert sorted(r["doc_id"] for r in left.collect()) == [d for d in want if not want[d][4]] and left.columns == docs.columns
    assert not decontam.contamination(docs, bench.limit(0)).where("contaminated").count()
    assert decontam.contamination(none, bench).count() == 0


@pytest.mark.parametrize("length", [400, 40])
def test_repeats(docs, none, texts, length):
    raw = [(t or "").encode() for t in texts]
    count = collections.Counter(b[p : p + length] for b in raw for p in range(len(b) - length + 1))
    got = {r["doc_id"]: r for r in repeats.removals(docs, length).collect()}
    for i, b in enumerate(raw):
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - length + 1):
            if count[b[p : p + length]] > 1:
                gone[p : p + length] = True
        kept = bytes(np.frombuffer(b, np.uint8)[~gone])
        spans = int(np.count_nonzero(np.diff(np.concatenate([[0], gone.astype(int)])) == 1))
        assert (got[i]["n_bytes"], got[i]["n_removed"], got[i]["n_spans"], bytes(got[i]["kept"])) == (len(b), int(gone.sum()), spans, kept), i
    assert repeats.removals(none).count() == 0


def test_repeats_of_full_buckets(docs, texts, monkeypatch):
    want = {r["doc_id"]: tuple(r) for r in repeats.removals(docs, 40).collect()}
    monkeypatch.setattr(repeats, "PER_BUCKET", 20)
    assert {r["doc_id"]: tuple(r) for r in repeats.removals(docs, 40).collect()} == want


def test_equal_neighbours_are_compared_by_bytes():
    b = np.frombuffer(b"abcdabceabcd", np.uint8)
    s = np.array([0, 4, 8])
    again, first = repeats._equal_neighbours(np.zeros(3, np.uint64), s, b, 4)  # all of one name
    assert again.tolist() == [True, False, True] and first.tolist() == [True, True, False]


@pytest.mark.parametrize("length", [3, 14, 40, 400, 2000])
def test_difference_covers(length):
    v, d = repeats.difference_cover(length)
    assert {(a - b) % v for a in d for b in d} == set(range(v)) and v <= max(1, length // 2)


def test_packing(docs, none, texts):
    tokenizers = pytest.importorskip("tokenizers")
    t = tokenizers.Tokenizer.from_file(packing.vocabulary_path("byte_bpe_50k.json"))
    want = {}
    texts = [*texts, "a <|endoftext|> b<|endoftext|>", "<|endoftext|>", "<|endoftext"]
    docs = docs.unionByName(docs.sparkSession.createDataFrame([(i, x) for i, x in enumerate(texts) if i >= len(texts) - 3], "doc_id long, text string"), allowMissingColumns=True)
    for i, x in enumerate(texts):
        ids = [*t.encode(x or "", add_special_tokens=False).ids, 2]
        first, at, k = len(ids) % 1024 or 1024, 0, 0
        while at < len(ids):
            n = first if k == 0 else 1024
            want[i, k] = (at, n, zlib.crc32(np.array(ids[at : at + n], "<u4").tobytes()))
            at, k = at + n, k + 1
    rows = packing.pack_documents(docs).collect()
    assert {(r["doc_id"], r["piece"]): (r["start"], r["length"], r["ids_crc32"]) for r in rows} == want
    by = collections.defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for x in by.values():
        x.sort()
        assert x[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(x, x[1:], strict=False)) and x[-1][0] + x[-1][1] <= 1024
    assert packing.pack_documents(none).count() == 0


def test_packing_of_repeated_rows_and_null_ids(spark):
    rows = spark.createDataFrame([(1, "a b"), (1, "a b"), (None, "a b"), (None, None), (2, "word " * 3000)], "doc_id long, text string")
    got = packing.pack_documents(rows).collect()
    assert collections.Counter((r["doc_id"], r["piece"]) for r in got if r["doc_id"] != 2) == {(1, 0): 2, (None, 0): 2}
    assert len({(r["sequence_id"], r["offset"]) for r in got}) == len(got) == 4 + len([r for r in got if r["doc_id"] == 2])


def test_bin_completion_of_very_many_equal_pieces():
    plan, bound = packing.complete_bins({1: 10**9, 500: 10**7, 1024: 5}, steps=10_000)
    assert sum(n for _, n in plan) == bound


@pytest.mark.parametrize("seed", range(12))
def test_bin_completion_is_optimal_on_small_cases(seed):
    r = random.Random(seed)
    sizes = [r.randint(1, 30) for _ in range(r.randint(1, 9))]

    def best(left, bins):
        if not left:
            return len(bins)
        out = len(bins) + len(left)
        for i in {b: i for i, b in enumerate(bins)}.values():
            if bins[i] >= left[0]:
                out = min(out, best(left[1:], bins[:i] + (bins[i] - left[0],) + bins[i + 1 :]))
        return min(out, best(left[1:], (*bins, 30 - left[0])))

    plan, bound = packing.complete_bins(dict(collections.Counter(sizes)), 30, steps=None)
    assert sum(n for _, n in plan) == best(tuple(sorted(sizes, reverse=True)), ()) >= bound
    assert collections.Counter({k: v for k, v in sum((collections.Counter({s: n * c.count(s) for s in set(c)}) for c, n in plan), collections.Counter()).items()}) == collections.Counter(sizes)


def test_sharding(docs, none, texts):
    rows = sharding.shard_documents(docs, 5).collect()
    size = {i: len((t or "").encode()) + 8 for i, t in enumerate(texts)}
    assert {r["doc_id"]: r["size"] for r in rows} == size
    assert all(r["text_crc32"] == zlib.crc32((texts[r["doc_id"]] or "").encode()) for r in rows)
    by = collections.defaultdict(list)
    for r in rows:
        by[r["shard"]].append(r)
    assert sorted(by) == list(range(5)) and all(sorted(r["slot"] for r in x) == list(range(len(x))) for x in by.values())
    loads = [sum(r["size"] for r in x) for x in by.values()]
    assert max(loads) - min(loads) <= 2 * max(size.values())
    assert sharding.shard_documents(none).count() == 0


def brute_shards(rows, shards):
    """shard of each row of (group, dims, weight): the same splits by sorting."""
    scale = [(min(c), max(c)) for c in zip(*(d for _, d, _ in rows), strict=True)]
    keys = [[(int((x - lo) * float((1 << 20) - 1) / float(max(1, hi - lo))), g) for x, (lo, hi) in zip(d, scale, strict=True)] for g, d, _ in rows]
    out = {}

    def split(own, first, n):
        if n == 1 or not own:
            out.update({i: first for i in own})
            return
        spread = [max(keys[i][k][0] for i in own) - min(keys[i][k][0] for i in own) for k in range(len(scale))]
        k = spread.index(max(spread))
        total, at, weights = sum(rows[i][2] for i in own), 0, collections.Counter()
        for i in own:
            weights[keys[i][k]] += rows[i][2]
        want, cut = total * (n // 2) / n, None
        for key in sorted(weights):
            if at + weights[key] >= want:
                cut = (key, want - at <= at + weights[key] - want)
                break
            at += weights[key]
        low = [i for i in own if keys[i][k] < cut[0] or keys[i][k] == cut[0] and not cut[1]]
        split(low, first, n // 2)
        split([i for i in own if i not in set(low)], first + n // 2, n - n // 2)

    split(list(range(len(rows))), 0, shards)
    return out


def test_sharding_is_that_of_sorted_medians(spark):
    r = random.Random(8)
    texts = ["w" * r.randint(1, 3000) + " x" * r.randint(0, 50) + "\n" * r.randint(0, 9) + "é" * r.randint(0, 40) for _ in range(200)]
    texts += [texts[3]] * 4
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    got = {x["doc_id"]: x["shard"] for x in sharding.shard_documents(docs, 6).collect()}
    tie = {x["text"]: (x["h"] >> 24) & ((1 << 40) - 1) for x in docs.select("text", F.xxhash64(F.xxhash64("text")).alias("h")).collect()}
    dims = lambda t: (len(t.encode()), len(t.encode()) - len(t), t.count("\n"), t.count(" "))
    assert got == brute_shards([(tie[t], dims(t), len(t.encode()) + 8) for t in texts], 6)
    assert len({got[i] for i in (3, 200, 201, 202, 203)}) == 1


def test_sharding_of_null_ids_and_repeated_rows(spark):
    rows = spark.createDataFrame([(None, "same")] * 40 + [(7, "same")] * 40 + [(1, None), (1, "")], "doc_id long, text string")
    got = sharding.shard_documents(rows, 4).collect()
    assert len(got) == 82 and {x["shard"] for x in got} == {0, 1, 2, 3}
    by = collections.Counter(x["shard"] for x in got)
    assert max(by.values()) - min(by.values()) <= 4 and all(sorted(x["slot"] for x in got if x["shard"] == k) == list(range(n)) for k, n in by.items())


def test_a_heavy_group_is_split(spark):
    rows = spark.createDataFrame([(i, "same text") for i in range(300)] + [(1000 + i, f"t{i}" * 3) for i in range(100)], "doc_id long, text string")
    loads = [r["n"] for r in sharding.shard_documents(rows, 8).groupBy("shard").agg(F.sum("size").alias("n")).collect()]
    assert len(loads) == 8 and max(loads) < 1.25 * min(loads)


def test_toxicity(spark, none):
    r = random.Random(5)
    fill = ["".join(r.choice("abcdefgh") for _ in range(5)) for _ in range(200)]
    rows, labels = [], []
    for i in range(600):
        bad = i % 5 == 1
        w = [r.choice(fill) for _ in range(40)] + (["vileness", "grimword", "vilely"] if bad else [])
        r.shuffle(w)
        rows.append((i, " ".join(w)))
        labels.append((i, int(bad)))
    rows += [(600, None), (601, "")]
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    model = toxicity.fit(docs, marks)
    got = {x["doc_id"]: x["score"] for x in toxicity.score_texts(docs, model, ["doc_id"]).collect()}
    assert all((got[i] >= 0.5) == bool(y) for i, y in labels) and got[600] == got[601] < 0.5
    # the neighbours are those of a full comparison
    doc, term, n = toxicity.term_counts(pa.array([t for _, t in rows]), toxicity.Lookup(model.hashes))
    w = toxicity.weights(doc, term, n, model.idf, len(rows))
    dense = np.zeros((len(model.index.label), len(model.hashes)))
    cells = np.repeat(np.arange(model.index.n_terms), np.diff(model.index.pointer))
    dense[model.index.example, cells] = model.index.weight
    for i in range(0, 600, 37):
        own = doc == i
        e, s = model.index.nearest(term[own], w[own])
        q = np.zeros(len(model.hashes))
        q[term[own]] = w[own]
        full = np.sort(dense @ q)[::-1]
        assert np.allclose(s, full[full > 0][: len(s)]) and len(s) == min(toxicity.NEIGHBOURS, int((full > 0).sum()))
    assert toxicity.drop_toxic(docs.withColumn("score", F.lit("x")).withColumn("row", F.lit(1)), marks).columns == ["doc_id", "text", "score", "row"]
    assert toxicity.fit(docs, marks.limit(0)).base == 0.0
    assert toxicity.score_texts(none, model, ["doc_id"]).count() == 0


def test_blocks_of_the_index_hide_no_neighbour():
    r = np.random.default_rng(5)
    for n in (1, 40, 700):
        topic = r.integers(0, 12, n)
        full = np.where(r.random((n, 400)) < np.where(np.arange(400) // 30 == topic[:, None], 0.5, 0.02), r.uniform(0.1, 3, (n, 400)), 0).astype(np.float32)
        full[:, 0] += 0.01  # no example without terms
        full[n // 2] = full[0]  # a tie
        e, t = np.nonzero(full)
        start = np.searchsorted(e, np.arange(n + 1))
        index = toxicity.InvertedIndex(start, t.astype(np.int32), full[e, t], np.zeros(n), np.ones(n), np.arange(n), 400)
        for skip in (None, np.arange(n)):
            found = {i: (x, c) for i, x, c in index.search(e, t, full[e, t].astype(float), skip=skip)}
            cosines = full.astype(float) @ full.T.astype(float)
            if skip is not None:
                np.fill_diagonal(cosines, 0)
            for i in range(n):
                expected = np.lexsort((np.arange(n), -np.round(cosines[i], 9)))[: toxicity.NEIGHBOURS]
                expected = expected[cosines[i][expected] > 0]
                assert np.allclose(found[i][1], cosines[i][expected]) and np.array_equal(np.sort(cosines[i][found[i][0]]), np.sort(cosines[i][expected]))


def test_the_index_holds_each_term_once_and_sums_postings_in_parts(monkeypatch):
    """op4: common terms were kept as postings beside their dense rows, and a text's postings were gathered all at once."""
    monkeypatch.setattr(toxicity, "POSTINGS", 7)
    rng = np.random.default_rng(11)
    n, m = 300, 60
    full = np.where(rng.random((n, m)) < np.linspace(0.5, 0.003, m), rng.random((n, m)), 0).astype(np.float32)
    full[:, -1] = 1e-3
    e, t = np.nonzero(full)
    start = np.concatenate([[0], np.cumsum(np.bincount(e, minlength=n))])
    index = toxicity.InvertedIndex(start, t.astype(np.int32), full[e, t], np.zeros(n), np.ones(n), np.arange(n), m)
    row, *_, pointer, at_place, weight = index.forms()
    assert 0 < pointer[-1] == len(at_place) == len(weight) == (row[t] < 0).sum() < len(t)
    query = rng.random((9, m)) * (rng.random((9, m)) < 0.4)
    query[:, -1] = 1
    doc, term = np.nonzero(query)
    for i, near, s in index.search(doc, term, query[doc, term]):
        cosines = query[i] @ full.T.astype(float)
        assert list(near) == list(np.lexsort((np.arange(n), -cosines))[: toxicity.NEIGHBOURS])
        assert np.allclose(s, cosines[near])


def test_toxicity_searches_texts_without_label_words(spark):
    r = random.Random(6)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    fill = [word() for _ in range(200)]
    rows = [(i, " ".join(r.choice(fill) for _ in range(30)) + (" grimword vileness" if i % 5 == 1 else "")) for i in range(300)]
    rows[1] = (1, "zzyzx " + " ".join(fill[:12]))  # a toxic example without any label word
    rows += [(1000, rows[1][1]), (1001, fill[3]), (1002, "zzyzx"), (1003, "unheardof")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    marks = spark.createDataFrame([(i, int(i % 5 == 1)) for i in range(300)], "doc_id long, toxic int")
    learnt = {x["doc_id"] for x in toxicity.learnable(marks).collect()}
    assert 1 in learnt
    model = toxicity.fit(docs, marks)
    got = {x["doc_id"]: x for x in toxicity.score_texts(docs, model, ["doc_id"]).collect()}
    assert (round(got[1000]["evidence"][0]["cosine"], 5), got[1000]["evidence"][0]["toxic"]) == (1.0, 1)
    assert got[1002]["evidence"][0]["toxic"] == 1 and all(got[i]["evidence"] for i in [*range(300), 1001])
    assert not got[1003]["evidence"] and got[1003]["score"] == model.base


def test_lines_that_repeat_themselves_are_alike_at_any_length(spark):
    text = "buy now and save big! " * 20
    docs = spark.createDataFrame([(i, text[:n]) for i, n in enumerate((120, 150, 230, 400))], "doc_id long, text string")
    got = {x["doc_id"]: x for x in line_dedup.judged_lines(docs).collect()}
    assert len({x["component"] for x in got.values()}) == 1 and [got[i]["kept"] for i in range(4)] == [True, False, False, False]


def test_alike_lines_share_a_key(spark):
    r = random.Random(1)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8)))
    runs = lambda x: {x[i : i + 9] for i in range(len(x) - 8)}
    rows = []
    while len(rows) < 4000:
        w = [word() for _ in range(45)]
        line = " ".join(w)
        alike = 1.0
        while alike > 0.85:
            w[r.randrange(45)] = word()
            a, b = runs(line), runs(" ".join(w))
            alike = len(a & b) / len(a | b)
        if alike >= 0.8:
            rows += [(len(rows), line), (len(rows) + 1, " ".join(w))]
    keys = {x["node"]: set(x["keys"]) for x in line_dedup.band_keys(spark.createDataFrame(rows, "node long, line string")).collect()}
    assert sum(not keys[i] & keys[i + 1] for i in range(0, 4000, 2)) <= 3


def test_the_driver_makes_no_postings_of_the_examples(spark):
    """op4: the index's postings and dense rows, and the examples' votes, were made on the driver."""
    docs = spark.createDataFrame([(i, f"word{i % 7} common text number{i} " + ("vile" if i % 3 == 0 else "mild")) for i in range(60)], "doc_id long, text string")
    model = toxicity.fit(docs, docs.select("doc_id", (F.col("doc_id") % 3 == 0).cast("int").alias("toxic")))
    assert len(model.bounds) and not {"pointer", "example", "weight", "_forms"} & set(model.index.__dict__)
    votes = [model.vote(*model.index.nearest(*model.index.of(e), skip=e)) for e in range(len(model.index.label))]
    bounds, values = toxicity.pooled(np.array(votes), model.index.label, model.index.vote)
    assert np.allclose(bounds, model.bounds) and np.allclose(values, model.values)
    scored = {r["doc_id"]: r["score"] for r in toxicity.score_texts(docs, model, ["doc_id"]).collect()}
    direct = model.score(pa.array([r["text"] for r in docs.orderBy("doc_id").collect()]))[0]
    assert np.allclose([scored[i] for i in range(60)], direct)


def test_line_shingles_stay_in_generated_code(spark):
    """pairs were verified by lambdas over arrays, and each shingle was compared with every part's least hash."""
    base = " ".join(f"word{i * i}" for i in range(40))
    text = [f"{base[: 200 + 9 * (i % 5)]} {i // 4} {i % 7} more" for i in range(60)] + ["é" * 7, "short", ""]
    lines = spark.createDataFrame(list(enumerate(text)), "node long, line string")
    shingles = [{t.encode()[i : i + 9] for i in range(max(1, len(t.encode()) - 8))} for t in text]
    pairs = [(i, j) for i in range(len(text)) for j in range(i)]
    verified = line_dedup.verified_lines(0.8)(spark.createDataFrame(pairs, "a long, b long"), lines)
    want = [(i, j) for i, j in pairs if len(shingles[i] & shingles[j]) >= 0.8 * len(shingles[i] | shingles[j])]
    assert sorted(map(tuple, verified.collect())) == want != []
    keys = line_dedup.band_keys(lines)
    for df in (verified, keys):
        assert "transform(" not in df._jdf.queryExecution().optimizedPlan().toString()
    plan = keys._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and plan.count("partial_min") == 3  # lines are shuffled, once


def test_the_driver_lets_its_tables_go_before_vectors_come(spark, monkeypatch):
    """The pipeline's toxicity stage was stopped for the driver's memory."""
    held, index = [], toxicity._index

    def spy(*args):
        held.extend(k for k, v in sys._getframe(1).f_locals.items() if isinstance(v, np.ndarray | pa.Table))
        return index(*args)

    monkeypatch.setattr(toxicity, "_index", spy)
    docs = spark.createDataFrame([(i, f"word{i % 9} and {'bad' if i % 3 else 'good'} thing") for i in range(60)], "doc_id long, text string")
    toxicity.fit(docs, spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(60)], "doc_id long, toxic int"))
    assert set(held) == {"hashes", "idf", "tied"}


def test_sketches_spare_pairs_and_lose_no_link(spark, monkeypatch):
    """every pair that shares a key had its shingles told apart, long lines most of all."""
    r = random.Random(3)
    text = []
    for n in (2, 30, 60, 250):
        for _ in range(4):
            w = [f"w{r.randrange(10**6)}" for _ in range(n)]
            for part in (0, 0.02, 0.05, 0.2, 0.4):
                text.append(" ".join(f"x{r.randrange(10**6)}" if r.random() < part else x for x in w))
    text += ["la " * 90, "la " * 400, "la " * 90 + "end of it", "abcdefghi" * 200, "abcdefghi" * 200 + text[-1], "", "é" * 30]
    shingles = [{t.encode()[i : i + 9] for i in range(max(1, len(t.encode()) - 8))} for t in text]
    pairs = [(i, j) for i in range(len(text)) for j in range(i)]
    alike = {(i, j) for i, j in pairs if len(shingles[i] & shingles[j]) >= 0.8 * len(shingles[i] | shingles[j])}
    lines = written(spark.createDataFrame(list(enumerate(text)), "node long, line string"), "lines")
    every = spark.createDataFrame([(0, i) for i in range(len(text))], "key long, node long")
    asked = set()

    def verify(some, texts):
        asked.update(map(tuple, some.select("a", "b").collect()))
        return line_dedup.verified_lines(0.8)(some, texts)

    sets = lambda x: pytest.fail("bounds by shingle sets aren't needed")
    roots = {x["node"]: x["root"] for x in linking.linked(every, lambda ids: lines, sets, verify, 0.8, line_dedup.SKETCHES).collect()}
    least = list(range(len(text)))
    for _ in text:
        for i, j in alike:
            least[i] = least[j] = min(least[i], least[j])
    assert [roots.get(i, i) for i in range(len(text))] == least and len(asked - alike) < len(pairs) // 20
    sketches = {n: {x["node"]: x for x in line_dedup.sketches(lines, n).collect()} for n in (line_dedup.WORDS, line_dedup.LONG_WORDS)}
    for n, of in sketches.items():
        differ = lambda i, j: sum(((of[i][f"w{k}"] ^ of[j][f"w{k}"]) & (2**64 - 1)).bit_count() for k in range(n))  # noqa: B023, E731
        assert all(differ(i, j) <= len(shingles[i] ^ shingles[j]) for i, j in pairs)


def test_linking_lets_broadcasts_go(spark, monkeypatch):
    """the driver was stopped in the line stage; broadcasts of 16 MB files stood there until the JVM happened to collect."""
    seen = []
    monkeypatch.setattr(linking, "let_go", seen.append)
    edges = spark.createDataFrame([(2, 1), (3, 2), (9, 8)], "a long, b long")
    assert {tuple(x) for x in components(edges).collect()} == {(1, 1), (2, 1), (3, 1), (8, 8), (9, 8)} and seen == [spark]
    large = written(spark.range(0, 1_000_000, 1, 1).select(F.xxhash64("id").alias("node")), "large")
    assert "broadcast" not in line_dedup.small(large)._jdf.queryExecution().logical().toString().lower()
