"""The candidate space: candidates (q, f, members), connections (q, f, q2, f2 in both directions), and its pruning."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .model import HypergraphFrame, member_labels, signature_hash
from .pattern import PatternGraph
from .storage import held


@dataclass
class CandidateSpace:
    candidates: DataFrame
    connections: DataFrame
    rounds: int = 0


def init_candidates(p: PatternGraph, h: HypergraphFrame) -> DataFrame:
    """q, f, members: edges with the signature (and edge label) of a query edge. Equal query signatures share one lookup."""
    spark = h.edges.sparkSession
    wanted: dict[tuple, list[int]] = {}
    for q, e in enumerate(p.edges):
        wanted.setdefault((tuple(p.signature(e)), p.elabels[q] if p.elabels else None), []).append(q)
    rows = [(list(sig), name, qs, signature_hash(sig)) for (sig, name), qs in wanted.items()]
    asked = spark.createDataFrame(rows, "_sig array<string>, _elabel string, qs array<int>, sig_id long")
    sizes, ids = sorted({len(r[0]) for r in rows}), sorted({r[3] for r in rows})
    # literals reach the scan: row groups are skipped by their statistics and bloom filters
    found = h.edges.where(F.col("arity").isin(sizes) & F.col("sig_id").isin(ids)).join(F.broadcast(asked), "sig_id").where(F.col("sig") == F.col("_sig"))
    if p.elabels:
        found = found.where(F.col("elabel").eqNullSafe(F.col("_elabel")))
    return found.select(F.explode("qs").alias("q"), F.col("e").alias("f"), "members")


def connected(members: Column, members2: Column, overlap: Column) -> Column:
    """The shared vertices of two data edges have the required signature."""
    return member_labels(F.array_intersect(members, members2)) == overlap


def connect(p: PatternGraph, candidates: DataFrame, adaptive: bool = True) -> DataFrame:
    """q, f, q2, f2: connected candidates of adjacent query edges.

    Candidates meet through one shared vertex of one label of the required overlap, the label that is rarest among the
    candidates' vertices, so hub vertices of common labels are not joined.
    """
    spark = candidates.sparkSession
    if not p.overlaps:
        return candidates.select("q", "f", F.col("q").alias("q2"), F.col("f").alias("f2")).limit(0)
    vertices = candidates.select("q", "f", F.inline("members"))
    common = {r["l"]: r["n"] for r in vertices.groupBy("l").agg(F.count("*").alias("n")).where(F.col("l").isin(sorted({x for s in p.overlaps.values() for x in s}))).collect()}
    rows = [(a, b, min(s, key=lambda x: (common.get(x, 0), x)), s) for (a, b), s in p.overlaps.items()]
    need = F.broadcast(spark.createDataFrame(rows, "a int, b int, _l string, overlap array<string>"))
    left = vertices.join(need, (F.col("q") == F.col("a")) & (F.col("l") == F.col("_l"))).select("a", "b", "v", F.col("f").alias("f1"))
    right = vertices.join(need, (F.col("q") == F.col("b")) & (F.col("l") == F.col("_l"))).select("a", "b", "v", F.col("f").alias("f2"))
    met = left.join(right, ["a", "b", "v"]).where("f1 <> f2").select("a", "b", "f1", "f2").distinct()
    one = candidates.select(F.col("q").alias("a"), F.col("f").alias("f1"), F.col("members").alias("m1"))
    two = candidates.select(F.col("q").alias("b"), F.col("f").alias("f2"), F.col("members").alias("m2"))
    exact = met.join(one, ["a", "f1"]).join(two, ["b", "f2"]).join(need.drop("_l"), ["a", "b"]).where(connected(F.col("m1"), F.col("m2"), F.col("overlap")))
    forth = exact.select(F.col("a").alias("q"), F.col("f1").alias("f"), F.col("b").alias("q2"), "f2")
    return forth.unionByName(forth.select(F.col("q2").alias("q"), F.col("f2").alias("f"), F.col("q").alias("q2"), F.col("f").alias("f2")))


def adjacent_candidates(connections: DataFrame, q: int, f, q2: int) -> DataFrame:
    return connections.where((F.col("q") == q) & (F.col("f") == f) & (F.col("q2") == q2)).select("f2")


def _needed(p: PatternGraph) -> Column:
    return F.element_at(F.array(*[F.lit(a).cast("long") for a in p.adjacent]), F.col("q") + 1)


def build_space(p: PatternGraph, h: HypergraphFrame) -> CandidateSpace:
    c = held(init_candidates(p, h), "candidates")
    return CandidateSpace(c, held(connect(p, c), "connections"))


def prune_to_fixpoint(p: PatternGraph, space: CandidateSpace, max_rounds: int | None = None) -> CandidateSpace:
    """Candidates stay while they have a connection to every adjacent query edge. Rounds of semi-joins until nothing changes."""
    c, k, rounds = space.candidates, space.connections, 0
    before = c.count()
    while max_rounds is None or rounds < max_rounds:
        bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("q2"))
        has = k.groupBy("q", "f").agg(F.bit_or(bit).alias("has"))
        kept = c.join(has, ["q", "f"], "left").where((F.coalesce("has", F.lit(0)).bitwiseAND(_needed(p))) == _needed(p)).drop("has")
        kept = held(kept, "candidates")
        after = kept.count()
        rounds += 1
        if after == before:
            return CandidateSpace(kept, k, rounds)
        ids = kept.select("q", "f")
        k = held(k.join(ids, ["q", "f"], "left_semi").join(ids.withColumnsRenamed({"q": "q2", "f": "f2"}), ["q2", "f2"], "left_semi").select("q", "f", "q2", "f2"), "connections")
        c, before = kept, after
    return CandidateSpace(c, k, rounds)


def prune_worklist(p: PatternGraph, space: CandidateSpace) -> CandidateSpace:
    """The same fixpoint by a worklist of directed pairs of query edges, one semi-join each."""
    c, k, steps = space.candidates, space.connections, 0
    todo = [pair for a, b in p.overlaps for pair in ((a, b), (b, a))]
    while todo:
        a, b = todo.pop(0)
        steps += 1
        has = k.where((F.col("q") == a) & (F.col("q2") == b)).select("q", "f").distinct()
        kept = held(c.where(F.col("q") != a).unionByName(c.where(F.col("q") == a).join(has, ["q", "f"], "left_semi").select(*c.columns)), "candidates")
        if kept.count() < c.count():
            ids = kept.select("q", "f")
            k = held(k.join(ids, ["q", "f"], "left_semi").join(ids.withColumnsRenamed({"q": "q2", "f": "f2"}), ["q2", "f2"], "left_semi").select("q", "f", "q2", "f2"), "connections")
            todo += [(x, a) for x in range(p.size) if p.adjacent[a] >> x & 1 and x != b and (x, a) not in todo]
        c = kept
    return CandidateSpace(c, k, steps)
