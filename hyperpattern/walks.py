"""Random-walk queries: all walks at once, one join with the incidence a step; every choice is the least md5, so it can be replayed anywhere."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .model import HypergraphFrame
from .pattern import PatternGraph
from .storage import held


def _draw(seed: int, query: Column, step: int, f: Column) -> Column:
    return F.struct(F.md5(F.concat_ws("|", F.lit(seed), query, F.lit(step), f.cast("string"))), f)


def sample(h: HypergraphFrame, size: int, n: int, seed: int = 0, max_vertices: int | None = None) -> DataFrame:
    """query, step, e: n walks of `size` distinct, connected edges; walks that get stuck or exceed max_vertices are left out."""
    inc = held(h.edges.select("e", F.explode(F.transform("members", lambda x: x["v"])).alias("v")), "incidence")
    # one pass over the edges, combined on the map side: a column for each walk holds its least draw
    firsts = h.edges.agg(*[F.min_by("e", _draw(seed, F.lit(i).cast("long"), 0, F.col("e"))).alias(f"e{i}") for i in range(n)])
    first = firsts.select(F.posexplode(F.array(*[f"e{i}" for i in range(n)])).alias("query", "e")).where("e is not null")
    walk = held(first.select(F.col("query").cast("long").alias("query"), F.lit(0).alias("step"), "e"), "walks")
    for step in range(1, size):
        reach = walk.join(inc, "e").select("query", "v").distinct().join(inc, "v").select("query", "e").distinct()
        fresh = reach.join(walk.select("query", "e"), ["query", "e"], "left_anti")
        chosen = fresh.groupBy("query").agg(F.min_by("e", _draw(seed, F.col("query"), step, F.col("e"))).alias("e")).select("query", F.lit(step).alias("step"), "e")
        walk = held(walk.unionByName(chosen), "walks")
    full = walk.groupBy("query").agg(F.count("*").alias("n")).where(F.col("n") == size).select("query")
    walk = walk.join(full, "query", "left_semi")
    if max_vertices is not None:
        small = walk.join(inc, "e").groupBy("query").agg(F.countDistinct("v").alias("n")).where(F.col("n") <= max_vertices).select("query")
        walk = walk.join(small, "query", "left_semi")
    return walk


def patterns(h: HypergraphFrame, walks: DataFrame) -> dict[int, PatternGraph]:
    """The walks as patterns; as many as were asked for, each of a few edges."""
    by: dict[int, list] = {}
    for r in walks.orderBy("query", "step").collect():
        by.setdefault(r["query"], []).append(r["e"])
    edges = held(h.edges.join(walks.select("e").distinct(), "e", "left_semi"), "walk-edges")
    return {q: PatternGraph.from_edges(edges, ids) for q, ids in by.items()}
