"""Exact tests of a mapping: by intersections of all subsets, by cells, and the incremental cell check of one candidate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .model import member_labels
from .pattern import PatternGraph


def _strings(values: list[str]) -> Column:
    return F.array(*[F.lit(x) for x in values]) if values else F.array().cast("array<string>")


def subset_test(p: PatternGraph, members: list[Column]) -> Column:
    """True if every non-empty subset of the edges meets in vertices of the right signature. members: one array for each query edge."""
    test = F.lit(True)
    for s, sig in p.subsets():
        common = members[s[0]]
        for q in s[1:]:
            common = F.array_intersect(common, members[q])
        test = test & (member_labels(common) == _strings(sig))
    return test


def with_members(p: PatternGraph, mapping: DataFrame, edges: DataFrame) -> DataFrame:
    """mapping (m0 .. mk-1) with columns x0 .. xk-1: the members of the data edges."""
    for q in range(p.size):
        mapping = mapping.join(edges.select(F.col("e").alias(f"m{q}"), F.col("members").alias(f"x{q}")), f"m{q}")
    return mapping


def valid_by_subsets(p: PatternGraph, mapping: DataFrame, edges: DataFrame) -> DataFrame:
    rows = with_members(p, mapping, edges)
    return rows.where(subset_test(p, [F.col(f"x{q}") for q in range(p.size)])).select(*[f"m{q}" for q in range(p.size)])


def valid_by_cells(p: PatternGraph, mapping: DataFrame, edges: DataFrame) -> DataFrame:
    """A mapping is valid if the counts of data vertices by (bitmap, label) are those of the query. Purely relational: no row holds a whole edge."""
    spark = mapping.sparkSession
    names = [f"m{q}" for q in range(p.size)]
    keyed = mapping.select(*names).distinct()
    long = keyed.select(*names, F.posexplode(F.array(*names)).alias("pos", "e"))
    rows = long.join(edges.select("e", F.inline("members")), "e")
    bits = rows.groupBy(*names, "v", "l").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("pos"))).alias("b"))
    counts = bits.groupBy(*names, "b", "l").agg(F.count("*").alias("n"))
    want: dict[tuple, int] = {}
    for v, b in p.bitmaps.items():
        want[b, p.label[v]] = want.get((b, p.label[v]), 0) + 1
    wanted = F.broadcast(spark.createDataFrame([(b, x, n) for (b, x), n in want.items()], "b long, l string, want long"))
    judged = counts.join(wanted, ["b", "l"], "left").groupBy(*names).agg(F.sum(F.when(F.col("n") == F.col("want"), 1).otherwise(-(10**6))).alias("good"))
    return judged.where(F.col("good") == len(want)).select(*names)


def query_cells(p: PatternGraph, q: Column, mask: Column) -> Column:
    """Sorted (bitmap, label) of query edge q's vertices when the edges of mask and q are mapped."""
    each = F.array(*[F.array(*[F.struct(F.lit(p.bitmaps[u]).cast("long").alias("b"), F.lit(p.label[u]).alias("l")) for u in e]) for e in p.edges])
    seen = mask.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), q))
    return F.sort_array(F.transform(F.element_at(each, q + 1), lambda x: F.struct(x["b"].bitwiseAND(seen).alias("b"), x["l"].alias("l"))))


def data_cells(members: Column, cells: Column, q: Column) -> Column:
    """The same of a data edge: the bitmap a vertex has so far (cells: map from vertex to bitmap), with q's bit."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), q)
    return F.sort_array(F.transform(members, lambda x: F.struct(F.coalesce(F.try_element_at(cells, x["v"]), F.lit(0).cast("long")).bitwiseOR(bit).alias("b"), x["l"].alias("l"))))


def cell_check(p: PatternGraph, members: Column, cells: Column, q: Column, mask: Column) -> Column:
    """The candidate keeps the mapping an embedding; no set is intersected."""
    return data_cells(members, cells, q) == query_cells(p, q, mask)


def extended_cells(members: Column, cells: Column, q: Column) -> Column:
    """cells with q's bit set for the members."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), q)
    fresh = F.map_from_entries(F.transform(members, lambda x: F.struct(x["v"], bit)))
    return F.map_zip_with(cells, fresh, lambda _, a, b: F.coalesce(a, F.lit(0).cast("long")).bitwiseOR(F.coalesce(b, F.lit(0).cast("long"))))
