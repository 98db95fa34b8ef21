"""Fuzzy line deduplication with DataFrame operations only.

Lines that are alike in their sets of byte shingles are one component; the first occurrence of a component stays. Equal
lines are one node from the start. The hashes of a line's shingles fall into BANDS * ROWS parts, the least of each part
is its MinHash, and ROWS of them are the key of a band. Pairs that share a key are links if the exact Jaccard similarity
of their shingle sets reaches the threshold.
"""

from __future__ import annotations

from functools import partial, reduce
from operator import add

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import linked, small
from .shared import table, text_or_empty, written

SHINGLE, THRESHOLD = 9, 0.8
BANDS, ROWS = 10, 3
#: Words of 64 bits in a line's sketch, and in the wider one of lines over LONG bytes, which fill the first.
WORDS, LONG, LONG_WORDS = 16, 512, 64
#: Pairs whose shingles a task tells apart, so that they fit its memory.
PAIRS = 2000


def _held(df: DataFrame, name: str, value: Column) -> DataFrame:
    """df with a column computed once for each row; the optimizer doesn't copy an exploded column into lambdas."""
    return df.select("*", F.explode(F.array(value)).alias(name))


def all_shingles(line: str, size: int = SHINGLE) -> Column:
    """32-bit hashes of all runs of `size` bytes, each once; a shorter line is one shingle. line: a binary column that is held."""
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.octet_length(line) - (size - 1)))
    return F.array_distinct(F.transform(starts, lambda i: F.hash(F.substring(line, i, F.lit(size)))))


def shingle_sets(lines: DataFrame) -> DataFrame:
    """node, values: the distinct shingle hashes of lines (node, line)."""
    return _held(lines.select("node", "line"), "_bytes", F.col("line").cast("binary")).select("node", all_shingles("_bytes").alias("values"))


def shingle_rows(lines: DataFrame, *keep: str) -> DataFrame:
    """keep, h: the hash of every shingle of lines (keep, line), copies too, as all_shingles makes them; exploding stays in generated code, which lambdas over arrays don't."""
    rows = _held(lines.select(*keep, "line"), "_bytes", F.col("line").cast("binary")).select(*keep, "_bytes")
    rows = rows.select(*keep, "_bytes", F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.octet_length("_bytes") - (SHINGLE - 1)))).alias("_i"))
    return rows.select(*keep, F.hash(F.substring("_bytes", F.col("_i"), F.lit(SHINGLE))).alias("h"))


def verified_lines(threshold: float):
    """verify(pairs, lines): lines are joined to the pairs, and their shingles are told apart there; a line is a tenth of its set."""

    def verify(pairs: DataFrame, lines: DataFrame) -> DataFrame:
        side = lambda c: lines.select(F.col("node").alias(c), F.col("line").alias(f"_{c}"))
        parts = max(1, -(-pairs.count() // PAIRS))
        both = pairs.join(side("a"), "a").join(side("b"), "b").repartition(parts, "a", "b")
        both = both.select("a", "b", F.posexplode(F.array("_a", "_b")).alias("_side", "line"))
        met = shingle_rows(both, "a", "b", "_side").groupBy("a", "b", "h").agg(F.min("_side").alias("_lo"), F.max("_side").alias("_hi"))
        met = met.groupBy("a", "b").agg(F.count(F.when(F.col("_lo") < F.col("_hi"), 1)).alias("_both"), F.count("*").alias("_all"))
        return met.where(F.col("_both") >= threshold * F.col("_all")).select("a", "b")

    return verify


def band_keys(lines: DataFrame) -> DataFrame:
    """node, keys for lines (node, line), each node once: the least hash of each of BANDS * ROWS parts of a line's shingles, ROWS of them a key.

    All lines are signed alike, by all their shingles. Lines are dealt by node, so a band's few least hashes are found
    without a shuffle of them; as columns of one row, each shingle would be compared with all BANDS * ROWS of them.
    """
    parts = max(int(lines.sparkSession.conf.get("spark.sql.shuffle.partitions")), lines.rdd.getNumPartitions())
    rows = shingle_rows(lines.select("node", "line").repartition(parts, "node"), "node").select("node", "h", F.pmod(F.shiftright("h", 4), F.lit(BANDS * ROWS)).alias("_part"))
    rows = rows.select("node", "h", F.expr(f"int(_part div {ROWS})").alias("_band"), (F.col("_part") % ROWS).alias("_row"))
    least = rows.groupBy("node", "_band").agg(*[F.min(F.when(F.col("_row") == i, F.col("h"))).alias(f"_{i}") for i in range(ROWS)])
    keys = least.select("node", "_band", F.xxhash64("_band", *[F.col(f"_{i}") for i in range(ROWS)]).alias("_key"))
    keys = keys.groupBy("node").agg(*[F.max(F.when(F.col("_band") == b, F.col("_key"))).alias(f"_{b}") for b in range(BANDS)])
    return keys.select("node", F.array_compact(F.array(*[F.col(f"_{b}") for b in range(BANDS)])).alias("keys"))


def sketches(lines: DataFrame, n: int = WORDS) -> DataFrame:
    """node, size, w0, w1, ... of lines (node, line), each node once: a bit is set if one of the line's shingles falls on it. size: its shingles, copies too."""
    parts = max(int(lines.sparkSession.conf.get("spark.sql.shuffle.partitions")), lines.rdd.getNumPartitions())
    word = F.pmod(F.shiftright("h", 6), F.lit(n)).alias("_word")
    rows = shingle_rows(lines.select("node", "line").repartition(parts, "node"), "node").select("node", word, F.expr("shiftleft(1L, h & 63)").alias("_bit"))
    words = rows.groupBy("node", "_word").agg(F.bit_or("_bit").alias("_bits"), F.count("*").alias("_n"))
    return words.groupBy("node").agg(F.sum("_n").alias("size"), *[F.coalesce(F.max(F.when(F.col("_word") == i, F.col("_bits"))), F.lit(0)).alias(f"w{i}") for i in range(n)])


def sketches_allow(x: str, y: str, threshold: float, n: int = WORDS) -> Column:
    """No pair at the threshold is denied: a bit in which the sketches differ is a shingle that one line has and the other hasn't, and copies of shingles only make room for more of those."""
    apart = reduce(add, [F.bit_count(F.col(f"{x}.w{i}").bitwiseXOR(F.col(f"{y}.w{i}"))) for i in range(n)])
    return apart * (1 + threshold) <= (F.col(f"{x}.size") + F.col(f"{y}.size")) * (1 - threshold) + 1e-6


#: For linked(): of all lines, and the wider ones of long lines.
SKETCHES = [
    (sketches, sketches_allow),
    (lambda lines: sketches(lines.where(F.octet_length("line") > LONG), LONG_WORDS), partial(sketches_allow, n=LONG_WORDS)),
]


def split_lines(docs: DataFrame) -> DataFrame:
    """doc_id, line_no (from 0), line of docs (doc_id, text); null texts have one empty line."""
    return docs.select("doc_id", F.posexplode(F.split(text_or_empty(), "\n", -1)).alias("line_no", "line"))


def countable(line: Column) -> Column:
    """Lines without a letter, digit or character beyond ASCII (blank lines, rules) are layout and always stay."""
    return line.rlike(r"[0-9A-Za-z\x{80}-\x{10FFFF}]")


def components_of_lines(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """digest, node, root of every distinct countable line that is in a component with others or occurs more than once.

    docs: doc_id, text. node numbers lines by a 64-bit hash of their bytes; should two lines share one, both are left out
    of the comparison and only their exact copies are found.
    """
    lines = split_lines(docs).where(countable(F.col("line")))
    known = written(lines.select(F.xxhash64("line").alias("node"), F.xxhash64(F.reverse("line")).alias("check")).groupBy("node").agg(F.count("*").alias("n"), F.min("check").alias("lo"), F.max("check").alias("hi")), "line-counts")
    clear = known.where("lo = hi")
    doubtful = written(known.where("lo <> hi").select("node"), "doubtful-lines")
    keys = written(band_keys(lines.select(F.xxhash64("line").alias("node"), "line")).join(small(doubtful), "node", "left_anti"), "line-bands")
    keys = keys.select(F.explode("keys").alias("key"), "node")

    def texts_of(ids: DataFrame) -> DataFrame:
        return lines.select(F.xxhash64("line").alias("node"), "line").join(small(ids), "node", "left_semi").dropDuplicates(["node"])

    roots = linked(keys, texts_of, shingle_sets, verified_lines(threshold), threshold, SKETCHES)
    alone = clear.where("n > 1").select("node").join(roots.select("node"), "node", "left_anti").select("node", F.col("node").alias("root"))
    return written(roots.unionByName(alone), "line-roots")


def judged_lines(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, line_no, component (null: no other line is alike), kept. In each component the line with the smallest doc_id and line_no stays; null ids come last."""
    roots = components_of_lines(docs, threshold)
    lines = split_lines(docs).select("doc_id", "line_no", F.when(countable(F.col("line")), F.xxhash64("line")).alias("node"))
    tagged = lines.join(small(roots), "node", "left").select("doc_id", "line_no", F.col("root").alias("component"))
    place = F.struct(F.col("doc_id").isNull().alias("n"), F.col("doc_id").alias("d"), F.col("line_no").alias("l"))
    first = written(tagged.where("component is not null").groupBy("component").agg(F.min(place).alias("first")), "first-lines")
    out = tagged.join(small(first), "component", "left")
    same = F.col("first.d").eqNullSafe(F.col("doc_id")) & (F.col("first.l") == F.col("line_no"))
    return out.select("doc_id", "line_no", "component", (F.col("component").isNull() | same).alias("kept"))


def op2_fuzzy_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line of every document with its component and whether it stays."""
    return judged_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


def without_repeated_lines(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs with the lines that don't stay cut from their texts, and n_chars (if there is one) set anew; all rows and columns stay.

    Lines are judged with documents in order of doc_id. A null text stays null. Rows with equal doc_id lose the same line
    numbers only where their lines are equal.
    """
    roots = components_of_lines(docs.select("doc_id", "text"), threshold)
    lines = split_lines(docs.select("doc_id", "text")).select("doc_id", "line_no", F.when(countable(F.col("line")), F.xxhash64("line")).alias("node"))
    tagged = lines.join(small(roots), "node").select("doc_id", "line_no", "node", F.col("root").alias("component"))
    place = F.struct(F.col("doc_id").isNull().alias("n"), F.col("doc_id").alias("d"), F.col("line_no").alias("l"))
    first = written(tagged.groupBy("component").agg(F.min(place).alias("first")), "first-lines")
    out = tagged.join(small(first), "component").where(~(F.col("first.d").eqNullSafe(F.col("doc_id")) & (F.col("first.l") == F.col("line_no"))))
    gone = written(out.groupBy("doc_id").agg(F.collect_set(F.struct("line_no", "node")).alias("_gone")), "repeated-lines")
    joined = docs.alias("d").join(small(gone).alias("g"), F.col("d.doc_id").eqNullSafe(F.col("g.doc_id")), "left").select("d.*", "g._gone")
    kept = F.filter(F.split("text", "\n", -1), lambda x, i: ~F.array_contains("_gone", F.struct(i.alias("line_no"), F.xxhash64(x).alias("node"))))
    joined = joined.withColumn("text", F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n")))
    if "n_chars" in docs.columns:
        kind = dict(docs.dtypes)["n_chars"]
        joined = joined.withColumn("n_chars", F.when(F.col("_gone").isNull(), F.col("n_chars")).otherwise(F.char_length("text")).cast(kind))
    return joined.select(*docs.columns)
