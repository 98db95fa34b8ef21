"""Benchmark decontamination by winnowing.

Documents and benchmark texts become word sequences. A fingerprint is the smallest of WINDOW consecutive hashes of
GRAM-word runs, so any span of GRAM + WINDOW - 1 = 13 equal words leaves an equal fingerprint on both sides. Documents
that share one are read again, and each shared fingerprint is extended to the 13-word windows around it, which are
compared with the benchmark's windows as text. Items below 13 words are one window each; a span that short guarantees
no winnowed hash, so for the lengths that occur all runs of that length are compared.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import small, table, text_or_empty, written

SPAN, GRAM = 13, 8
WINDOW = SPAN - GRAM + 1
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What is not in a word: ASCII other than digits and letters. Written out one by one, since the regex engine looks single
#: characters up in a bit table and tries ranges one after the other, at ten times the cost. Possessive: a word is never given back.
BETWEEN = "".join(rf"\x{c:02X}" for c in range(128) if not chr(c).isalnum())
WORD = f"[^{BETWEEN}]++"


def words(text: Column) -> Column:
    """Only A-Z change case; lower() is used where that is all it can do."""
    plain = F.octet_length(text) == F.char_length(text)
    return F.regexp_extract_all(F.when(plain, F.lower(text)).otherwise(F.translate(text, UPPER, LOWER)), F.lit(WORD), F.lit(0))


def _pairs(array: Column, apart: int, make) -> Column:
    """make(x, y) for all elements x and y that stand `apart` places from each other."""
    n = F.greatest(F.size(array) - apart, F.lit(0))
    return F.zip_with(F.slice(array, 1, n), F.slice(array, apart + 1, n), make)


def _held(df: DataFrame, name: str, value: Column) -> DataFrame:
    """df with a column computed once for each row; the optimizer doesn't copy an exploded column into the lambdas that use it."""
    return df.select("*", F.explode(F.array(value)).alias(name))


def with_gram_hashes(df: DataFrame, n: int) -> DataFrame:
    """df (with words w) with h: the hash of the n words from each place, made of hashes of runs of half the length."""
    df = _held(df, "_h1", F.transform("w", lambda x: F.xxhash64(x)))
    have = 1
    while have < n:
        step = min(have, n - have)
        df = _held(df, f"_h{have + step}", _pairs(F.col(f"_h{have}"), step, lambda x, y: F.xxhash64(x, y)))
        have += step
    return df.withColumnRenamed(f"_h{n}", "h").drop(*[c for c in df.columns if c.startswith("_h") and c != f"_h{n}"])


def with_winnowed(df: DataFrame) -> DataFrame:
    """df (with hashes h) with marks: the minima of WINDOW consecutive hashes, and the minimum of a shorter sequence."""
    df = _held(df, "_m1", F.col("h"))
    have = 1
    while have < WINDOW:
        step = min(have, WINDOW - have)
        df = _held(df, f"_m{have + step}", _pairs(F.col(f"_m{have}"), step, lambda x, y: F.least(x, y)))
        have += step
    marks = F.when(F.size("h") < WINDOW, F.array_compact(F.array(F.array_min("h")))).otherwise(F.col(f"_m{WINDOW}"))
    return df.withColumn("marks", F.array_distinct(marks)).drop(*[c for c in df.columns if c.startswith("_m")])


def _window_text(array: Column, start: Column, n) -> Column:
    return F.array_join(F.slice(array, start, n), " ")


def benchmark_windows(bench: DataFrame, id_col: str) -> DataFrame:
    """window (its words joined by a space), n, item: one row for each item and window it has. Null texts have no words."""
    items = bench.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("item"), words(text_or_empty()).alias("w")).where(F.size("w") > 0)
    n = F.least(F.size("w"), F.lit(SPAN))
    items = items.select("item", "w", n.alias("n"))
    starts = F.explode(F.sequence(F.lit(1), F.size("w") - F.col("n") + 1))
    return items.select("item", "w", "n", starts.alias("s")).select("item", "n", _window_text(F.col("w"), F.col("s"), F.col("n")).alias("window")).distinct()


def prints(frame: DataFrame, n: int) -> DataFrame:
    """frame (with words w) with marks: the fingerprints that guarantee to meet equal spans of n words."""
    if n == SPAN:
        return with_winnowed(with_gram_hashes(frame, GRAM)).drop("h")
    return with_gram_hashes(frame, n).withColumn("marks", F.array_distinct("h")).drop("h")


def shared_prints(docs: DataFrame, key: list[str], windows: DataFrame, lengths: list[int]) -> DataFrame:
    """key columns, n_words, n, f in one pass over docs (key columns, text): a row with null n and f for each row of docs, and one for each fingerprint that a document shares with the benchmark's windows of n words."""
    distinct = windows.select("window", "n").distinct()
    known = [prints(distinct.where(F.col("n") == n).select(F.split("window", " ").alias("w")), n).select(F.lit(n).alias("n"), F.explode("marks").alias("f")) for n in lengths]
    met = known[0]
    for x in known[1:]:
        met = met.unionByName(x)
    met = written(met.distinct(), "benchmark-prints")
    out = _held(docs.select(*key, text_or_empty().alias("text")), "w", words(F.col("text"))).select(*key, "w", F.size("w").cast("long").alias("n_words"))
    marks = F.array(F.lit(None).cast("long"))
    for n in lengths:
        out = _held(prints(out, n), f"_p{n}", F.col("marks")).drop("marks")
        marks = F.concat(marks, F.col(f"_p{n}"))
    spread = out.select(*key, "n_words", F.explode(marks).alias("f"))
    return spread.join(small(met), "f", "left").where("n is not null or f is null").select(*key, "n_words", "n", "f")


def hits(docs: DataFrame, key: list[str], windows: DataFrame, shared: DataFrame, lengths: list[int]) -> DataFrame:
    """key columns, s, n, window: the places at which a benchmark window occurs in a document. shared: key columns, n, fs (shared fingerprints)."""
    found = []
    distinct = written(windows.select("window", "n").distinct(), "benchmark-windows")
    for n in lengths:
        gram = GRAM if n == SPAN else n
        of_n = written(shared.where(F.col("n") == n).drop("n"), "to-extend")
        again = docs.join(small(of_n), _same(docs, of_n, key)).select(*[docs[k] for k in key], "text", "fs")
        again = with_gram_hashes(_held(again, "w", words(text_or_empty())).drop("text"), gram)
        places = F.filter(F.transform("h", lambda h, i: F.when(F.array_contains("fs", h), i + 1)), lambda i: i.isNotNull())
        again = again.select(*key, "w", F.explode(places).alias("at"))
        spots = again.select(*key, "w", F.explode(F.sequence(F.greatest(F.lit(1), F.col("at") - (n - gram)), F.least(F.col("at"), F.greatest(F.lit(1), F.size("w") - n + 1)))).alias("s"))
        spots = spots.select(*key, "s", _window_text(F.col("w"), F.col("s"), F.lit(n)).alias("window"))
        found.append(spots.join(small(distinct), "window").where(F.col("n") == n).select(*key, "s", "n", "window"))
    out = found[0]
    for x in found[1:]:
        out = out.unionByName(x)
    return out


def _same(a: DataFrame, b: DataFrame, key: list[str]) -> Column:
    same = F.lit(True)
    for k in key:
        same = same & a[k].eqNullSafe(b[k])
    return same


def contamination(docs: DataFrame, bench: DataFrame, id_col: str = "item_id") -> DataFrame:
    """doc_id, text_hash, n_words, n_hit, n_items, items_sha256, contaminated; one row for each row of docs.

    docs: doc_id, text. Null and empty texts have no words and are clean; equal rows get equal answers; an empty
    benchmark leaves every document clean.
    """
    docs = docs.select("doc_id", "text", F.xxhash64(text_or_empty()).alias("text_hash"))
    key = ["doc_id", "text_hash"]
    windows = written(benchmark_windows(bench, id_col), "benchmark-items")
    lengths = sorted(r[0] for r in windows.select("n").distinct().collect())  # at most 13 values
    if not lengths:
        return _with_result(docs.select(*key, F.size(words(text_or_empty())).cast("long").alias("n_words")), None)
    met = written(shared_prints(docs, key, windows, lengths), "shared-prints")
    sizes = met.where("f is null").select(*key, "n_words")
    shared = written(met.where("f is not null").groupBy(*key, "n").agg(F.collect_set("f").alias("fs")), "prints-by-document")
    spots = written(hits(docs, key, windows, shared, lengths).distinct(), "benchmark-hits")
    spans = F.array_sort(F.collect_list(F.struct("s", "n")))
    covered = F.aggregate(
        spans,
        F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("count")),
        lambda a, x: F.struct(F.greatest(a["end"], x["s"] + x["n"]).alias("end"), (a["count"] + F.greatest(F.lit(0), x["s"] + x["n"] - F.greatest(a["end"], x["s"]))).alias("count")),
        lambda a: a["count"],
    )
    n_hit = spots.groupBy(*key).agg(covered.alias("n_hit"))
    items = spots.select(*key, "window").distinct().join(small(windows), "window").select(*key, "item").distinct()
    items = items.groupBy(*key).agg(F.count("*").alias("n_items"), F.sha2(F.array_join(F.array_sort(F.collect_list("item")), ",").cast("binary"), 256).alias("items_sha256"))
    hit = n_hit.join(items, _same(n_hit, items, key)).select(*[n_hit[k] for k in key], "n_hit", "n_items", "items_sha256")
    return _with_result(sizes, written(hit, "benchmark-result"))


def _with_result(sizes: DataFrame, hit: DataFrame | None) -> DataFrame:
    if hit is not None:
        out = sizes.join(small(hit), _same(sizes, hit, ["doc_id", "text_hash"]), "left").select(sizes["doc_id"], sizes["text_hash"], "n_words", "n_hit", "n_items", "items_sha256")
    else:
        out = sizes.select("*", F.lit(None).cast("long").alias("n_hit"), F.lit(None).cast("long").alias("n_items"), F.lit(None).cast("string").alias("items_sha256"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long")
    out = out.withColumns({"n_hit": zero("n_hit"), "n_items": zero("n_items"), "items_sha256": F.coalesce("items_sha256", F.sha2(F.lit("").cast("binary"), 256))})
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def op7_winnowing_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document against every benchmark item."""
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("text_hash")


def drop_contaminated(docs: DataFrame, bench: DataFrame, id_col: str = "item_id") -> DataFrame:
    """docs without the contaminated rows; all columns stay."""
    flagged = contamination(docs, bench, id_col).where("contaminated").select("doc_id", "text_hash").distinct()
    flagged = written(flagged, "contaminated")
    mark = docs.withColumn("_text_hash", F.xxhash64(text_or_empty()))
    return mark.join(small(flagged), mark["doc_id"].eqNullSafe(flagged["doc_id"]) & (mark["_text_hash"] == flagged["text_hash"]), "left_anti").drop("_text_hash")
