"""OVERLAP: every row stores the intersections of all subsets of its edges that meet in the query; a new edge is intersected with each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HypergraphFrame, member_labels
from ..order import static_order
from ..pattern import PatternGraph
from .profile import counts


def match(h: HypergraphFrame, p: PatternGraph) -> DataFrame:
    order = static_order(p, counts(h, p))
    edge = lambda q: h.edges.where(F.array_join("sig", "|") == "|".join(p.signature(p.edges[q]))).select(F.col("e").alias(f"m{q}"), F.col("members").alias(f"x{q}"))
    q = order[0]
    rows = edge(q).withColumnRenamed(f"x{q}", f"s{1 << q}")
    lattice = {1 << q: set(p.edges[q])}
    for n, q in enumerate(order[1:], 1):
        before = next((b for b in order[:n] if p.adjacent[q] >> b & 1), None)
        if before is None:
            rows = rows.crossJoin(edge(q))
        else:
            shared = min(p.signature(set(p.edges[q]) & set(p.edges[before])))
            vertices = lambda c: F.explode(F.transform(F.filter(c, lambda x: x["l"] == shared), lambda x: x["v"])).alias("v")  # noqa: E731, B023
            names = [c for c in rows.columns if c.startswith("m")]
            met = rows.select(*rows.columns, vertices(f"s{1 << before}")).join(edge(q).select("*", vertices(f"x{q}")), "v").drop("v")
            rows = met.dropDuplicates([*names, f"m{q}"])
        test, fresh = F.lit(True), {}
        for s, common in lattice.items():
            want = common & set(p.edges[q])
            found = F.array_intersect(f"s{s}", f"x{q}")
            test = test & (member_labels(found) == F.array(*[F.lit(x) for x in p.signature(want)]).cast("array<string>"))
            if want:
                fresh[s | 1 << q] = (want, found)
        rows = rows.where(test).withColumns({f"s{s}": c for s, (_, c) in fresh.items()}).withColumnRenamed(f"x{q}", f"s{1 << q}")
        lattice |= {s: w for s, (w, _) in fresh.items()} | {1 << q: set(p.edges[q])}
    return rows.select(*[f"m{q}" for q in range(p.size)])
