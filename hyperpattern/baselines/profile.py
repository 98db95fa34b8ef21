"""PROFILE: one static order; candidates come from an inverted index through a vertex of a mapped edge, and vertex profiles verify.

A vertex's profile is its label and the positions of the mapped edges it lies in; the multiset of the profiles of all
vertices touched must be the query's.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import HypergraphFrame, signature_hash
from ..order import static_order
from ..pattern import PatternGraph
from ..storage import held


def index(h: HypergraphFrame) -> DataFrame:
    """The inverted index: v, sig_id, e. A signature is as long as its edge, so a row holds its hash; the profiles tell signatures of one hash apart."""
    return h.edges.select("sig_id", "e", F.inline("members")).select("v", "sig_id", "e")


def profiles(members: list[Column]) -> Column:
    """Sorted (label, positions) of every distinct vertex of these edges."""
    everything = F.array_distinct(F.flatten(F.array(*members)))
    at = lambda x: F.array_join(F.filter(F.array(*[F.when(F.array_contains(m, x), F.lit(str(i))) for i, m in enumerate(members)]), lambda y: y.isNotNull()), ",")
    return F.sort_array(F.transform(everything, lambda x: F.concat_ws(":", x["l"], at(x))))


def query_profiles(p: PatternGraph, order: list[int]) -> Column:
    seen = sorted({u for q in order for u in p.edges[q]}, key=str)
    values = sorted(f"{p.label[u]}:{','.join(str(i) for i, q in enumerate(order) if u in p.edges[q])}" for u in seen)
    return F.array(*[F.lit(x) for x in values])


def counts(h: HypergraphFrame, p: PatternGraph) -> list[int]:
    sigs = ["|".join(p.signature(e)) for e in p.edges]
    have = {r["sig"]: r["n_edges"] for r in h.signature_partitions().where(F.col("sig").isin(sigs)).collect()}
    return [have.get(s, 0) for s in sigs]


def match(h: HypergraphFrame, p: PatternGraph, inverted: DataFrame | None = None) -> DataFrame:
    """inverted: index(h), if it is there already."""
    order = static_order(p, counts(h, p))
    inverted = held(index(h), "inverted") if inverted is None else inverted
    sig = lambda q: "|".join(p.signature(p.edges[q]))
    q = order[0]
    rows = h.edges.where(F.array_join("sig", "|") == sig(q)).select(F.col("e").alias(f"m{q}"), F.col("members").alias(f"x{q}"))
    for n, q in enumerate(order[1:], 1):
        edges = h.edges.select(F.col("e").alias(f"m{q}"), F.col("members").alias(f"x{q}"))
        before = next((b for b in order[:n] if p.adjacent[q] >> b & 1), None)
        if before is None:
            rows = rows.crossJoin(edges.where(F.array_join(F.sort_array(F.transform(f"x{q}", lambda x: x["l"])), "|") == sig(q)))
        else:
            near = rows.select(*rows.columns, F.explode(F.transform(f"x{before}", lambda x: x["v"])).alias("v"))
            near = near.join(inverted.where(F.col("sig_id") == signature_hash(p.signature(p.edges[q]))).select("v", F.col("e").alias(f"m{q}")), "v").drop("v")
            near = near.dropDuplicates([c for c in near.columns if c.startswith("m")])
            rows = near.join(edges, f"m{q}")
        rows = rows.where(profiles([F.col(f"x{i}") for i in order[: n + 1]]) == query_profiles(p, order[: n + 1]))
    if p.size == 1:
        rows = rows.where(profiles([F.col(f"x{order[0]}")]) == query_profiles(p, order))
    return rows.select(*[f"m{q}" for q in range(p.size)])
