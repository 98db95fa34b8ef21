"""BRUTE: the product of the signature candidates, and the test of all subsets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..candidates import init_candidates
from ..cells import subset_test
from ..model import HypergraphFrame
from ..pattern import PatternGraph
from ..storage import held


def match(h: HypergraphFrame, p: PatternGraph) -> DataFrame:
    c = held(init_candidates(p, h), "candidates")
    of = lambda q: c.where(F.col("q") == q).select(F.col("f").alias(f"m{q}"), F.col("members").alias(f"x{q}"))
    rows = of(0)
    for q in range(1, p.size):
        rows = rows.crossJoin(of(q))
    return rows.where(subset_test(p, [F.col(f"x{q}") for q in range(p.size)])).select(*[f"m{q}" for q in range(p.size)])
