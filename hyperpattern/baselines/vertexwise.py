"""VERTEXWISE: query vertices are mapped one by one through the incidence table; vertex mappings with equal edges are one embedding."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HypergraphFrame
from ..pattern import PatternGraph


def match(h: HypergraphFrame, p: PatternGraph) -> DataFrame:
    i = h.edges.select("e", "arity", F.inline("members"))
    rows, mapped, opened = None, {}, set()
    todo = list(range(p.size))
    while todo:
        q = next((x for x in todo if any(u in mapped for u in p.edges[x])), todo[0])
        todo.remove(q)
        for u in sorted(p.edges[q], key=lambda x: (x not in mapped, str(x))):
            name = f"v{len(mapped)}" if u not in mapped else mapped[u]
            side = i.where((F.col("l") == p.label[u]) & (F.col("arity") == len(p.edges[q]))).select(F.col("e").alias(f"m{q}"), F.col("v").alias(name))
            keys = ([f"m{q}"] if q in opened else []) + ([name] if u in mapped else [])
            if rows is None:
                rows = side
            elif keys:
                rows = rows.join(side, keys)
            else:
                rows = rows.crossJoin(side)
            if u not in mapped:
                for other in mapped.values():
                    rows = rows.where(F.col(name) != F.col(other))
                mapped[u] = name
            opened.add(q)
    return rows.select(*[f"m{q}" for q in range(p.size)]).distinct()
