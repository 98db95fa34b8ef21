"""Connected components and candidate linking with DataFrame operations only.

Union-find by contraction: every node takes its smallest neighbour as parent, parents are followed twice, edges are
rewritten to parents, and the map from nodes to roots is carried along, until no edge is left. A round at least halves
the nodes that still have edges, and no node, edge or root is ever on the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shared
from .shared import forget, let_go, written

#: Linking makes many joins one after the other, so what it broadcasts at once is less: the driver holds each table in several forms until its broadcast is let go.
BROADCAST_BYTES = 4 << 20


def small(df: DataFrame) -> DataFrame:
    return shared.small(df, BROADCAST_BYTES)


def components(edges: DataFrame) -> DataFrame:
    """node, root of every node in edges (a, b: long, not null); root is the smallest node of its component."""
    let_go(edges.sparkSession)  # broadcasts of the joins before stay on the driver until a collection there
    edges = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    roots = None
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        parent = written(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("parent")), "parents")
        up = small(parent)
        for _ in range(2):
            higher = up.select(F.col("node").alias("parent"), F.col("parent").alias("_above"))
            parent = parent.join(higher, "parent", "left").select("node", F.coalesce("_above", "parent").alias("parent"))
        parent = written(parent, "parents")
        up = small(parent)
        over = lambda frame, c: frame.join(up.withColumnRenamed("node", c).withColumnRenamed("parent", f"_{c}"), c, "left").withColumn(c, F.coalesce(f"_{c}", c)).drop(f"_{c}")  # noqa: E731, B023
        fresh = written(over(over(edges, "a"), "b").where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
        if roots is None:
            roots = parent.withColumnRenamed("parent", "root")
        else:
            old, roots = roots, written(over(roots, "root"), "roots")
            if hasattr(old, "_written_path"):
                forget(old)
        forget(edges)
        edges = fresh
    return roots if roots is not None else edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


#: Rounds in which members are compared with a few of their bucket, and with how many.
FEW_ROUNDS, FEW = 1, 4
#: Classes of elements, by hash, in which two sets' sizes bound what they share.
CLASSES = 32
#: Up to so many pairs for each node in doubt are compared without bounds first.
PAIRS_A_NODE = 2


def verified_by_sets(sets: Callable[[DataFrame], DataFrame], threshold: float) -> Callable[[DataFrame, DataFrame], DataFrame]:
    """verify(pairs, texts) that makes each text's set once, and joins the sets to the pairs."""

    def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
        ids = written(pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct(), "candidates")
        found = written(sets(texts.join(small(ids), "node", "left_semi")), "candidate-sets")
        left = found.select(F.col("node").alias("a"), F.col("values").alias("x"))
        right = found.select(F.col("node").alias("b"), F.col("values").alias("y"))
        return pairs.join(left, "a").join(right, "b").where(alike(F.col("x"), F.col("y"), threshold)).select("a", "b")

    return verify


def alike(x: Column, y: Column, threshold: float) -> Column:
    """The Jaccard similarity of two arrays of distinct elements is at least the threshold."""
    both = F.size(F.array_intersect(x, y))
    return both >= threshold * (F.size(x) + F.size(y) - both)


def linked(bands: DataFrame, texts_of: Callable[[DataFrame], DataFrame], sets: Callable[[DataFrame], DataFrame], verify: Callable[[DataFrame, DataFrame], DataFrame], threshold: float, sketches: Sequence[tuple[Callable[[DataFrame], DataFrame], Callable[[str, str, float], Column]]] = ()) -> DataFrame:
    """node, root of all nodes with a link. bands: key, node; texts_of(ids) gives the texts of a written table of nodes, once; sets(texts) gives node, values (distinct numbers); verify(pairs, texts) keeps the pairs that are links.
    sketches: (node and other columns of texts; whether those of x and y allow a link), made once and asked before any pair is verified; the first has all nodes, others may lack some.

    Members of a bucket are first compared with its smallest node. Then, for a few rounds, those outside the bucket's
    largest component are compared with some of it, drawn by hash. Last, whatever still lies in different components of
    one bucket is compared pair by pair. A pair that is never compared is already connected, or can't be a link: elements
    that no other set has are in no intersection, and of the others, two sets share in each class at most what the one
    with fewer has there.
    """
    shared = written(bands.groupBy("key").agg(F.min("node").alias("first"), F.max("node").alias("last")).where("first < last"), "buckets")
    members = written(bands.join(small(shared), "key").select("key", "node", "first"), "members")
    texts = written(texts_of(written(members.select("node").distinct(), "candidates")), "candidate-texts")
    made = [(written(make(texts), "sketches"), allow(x="x", y="y", threshold=threshold)) for make, allow in sketches]

    def able(pairs: DataFrame, since: int = 0) -> DataFrame:
        for table, allowed in made[since:]:
            both = pairs.join(small(table).alias("x"), F.col("a") == F.col("x.node"), "left").join(small(table).alias("y"), F.col("b") == F.col("y.node"), "left")
            pairs = written(both.where(F.col("x.node").isNull() | F.col("y.node").isNull() | allowed).select("a", "b"), "able-pairs")
        return pairs

    tried = written(_pairs(members, "first"), "pairs")
    edges = written(verify(able(tried), texts), "links")
    roots = components(edges)
    for r in range(FEW_ROUNDS):
        apart = written(_apart(members, roots), "apart")
        if apart.isEmpty():
            return roots
        most = apart.groupBy("key", "root").agg(F.count("*").alias("n")).groupBy("key").agg(F.max_by("root", F.struct("n", "root")).alias("main"))
        of_main = apart.join(most, "key")
        draws = [F.min_by("node", F.xxhash64("node", F.lit(r * FEW + i))).alias(f"_m{i}") for i in range(FEW)]
        drawn = of_main.where("root = main").groupBy("key").agg(*draws)
        outside = of_main.where("root <> main").join(drawn, "key").select("node", F.explode(F.array_distinct(F.array(*[f"_m{i}" for i in range(FEW)]))).alias("other"))
        pairs = written(_pairs(outside, "other").join(tried, ["a", "b"], "left_anti"), "pairs")
        if pairs.isEmpty():
            break
        tried = written(tried.unionByName(pairs), "tried-pairs")
        edges = written(edges.unionByName(verify(able(pairs), texts)), "links")
        roots = components(edges)
    apart = written(_apart(members, roots), "apart")
    if apart.isEmpty():
        return roots
    known, near = (apart.join(small(made[0][0]), "node"), made[0][1]) if made else _bounds(apart, texts, sets, threshold)
    known = known.join(known.groupBy("node").agg(F.collect_list("key").alias("keys")), "node")
    x, y = known.alias("x"), known.alias("y")
    once = F.col("x.key") == F.array_min(F.array_intersect("x.keys", "y.keys"))  # a pair that shares buckets is met in one of them
    rest = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.root") < F.col("y.root")) & near & once)
    rest = rest.select(F.greatest("x.node", "y.node").alias("a"), F.least("x.node", "y.node").alias("b")).distinct().join(tried, ["a", "b"], "left_anti")
    rest = written(rest, "pairs")
    if rest.isEmpty():
        return roots
    return components(edges.unionByName(verify(able(rest, 1), texts)))


def _bounds(apart: DataFrame, texts: DataFrame, sets: Callable[[DataFrame], DataFrame], threshold: float) -> tuple[DataFrame, Column]:
    """(apart with what bounds need, whether x and y allow a link). Few enough pairs are compared at once, more are first bounded."""
    by_root = apart.groupBy("key", "root").agg(F.count("*").alias("n")).groupBy("key").agg(((F.sum("n") * F.sum("n") - F.sum(F.col("n") * F.col("n"))) / 2).alias("p"))
    many = by_root.agg(F.sum("p")).first()[0] > PAIRS_A_NODE * apart.select("node").distinct().count()
    return (_bounded(apart, texts, sets, threshold), _reach(threshold)) if many else (apart, F.lit(True))


def _bounded(apart: DataFrame, texts: DataFrame, sets: Callable[[DataFrame], DataFrame], threshold: float) -> DataFrame:
    """apart with size, common (elements that other sets have too) and by_class (those by class), without nodes that can't reach the threshold with any."""
    of_apart = sets(texts.join(small(written(apart.select("node").distinct(), "candidates")), "node", "left_semi"))
    elements = of_apart.select("node", F.explode("values").alias("v"))
    met = written(elements.groupBy("v").agg(F.count("*").alias("n")).where("n > 1").select("v"), "common-elements")
    counts = [F.count(F.when(F.pmod(F.col("v"), F.lit(CLASSES)) == i, F.col("met"))).cast("int") for i in range(CLASSES)]
    sizes = elements.join(met.withColumn("met", F.lit(1)), "v", "left").groupBy("node").agg(F.count("*").alias("size"), F.count("met").alias("common"), F.array(*counts).alias("by_class"))
    sizes = written(sizes, "common-sizes")
    return apart.join(sizes, "node").where(F.col("common") >= threshold * F.col("size"))


def _reach(threshold: float) -> Column:
    """The bounds of x and y allow the threshold."""
    reaches = lambda n: n >= threshold * (F.col("x.size") + F.col("y.size") - n)
    by_class = F.aggregate(F.zip_with("x.by_class", "y.by_class", lambda i, j: F.least(i, j)), F.lit(0), lambda n, i: n + i)
    return reaches(F.least("x.common", "y.common")) & reaches(by_class)


def _pairs(frame: DataFrame, other: str) -> DataFrame:
    return frame.where(F.col("node") != F.col(other)).select(F.greatest("node", other).alias("a"), F.least("node", other).alias("b")).distinct()


def _apart(members: DataFrame, roots: DataFrame) -> DataFrame:
    """key, node, root of members of buckets that hold several components."""
    rooted = members.join(small(roots) if hasattr(roots, "_written_path") else roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root"))
    mixed = rooted.groupBy("key").agg(F.min("root").alias("_lo"), F.max("root").alias("_hi")).where("_lo < _hi").select("key")
    return rooted.join(mixed, "key", "left_semi")
