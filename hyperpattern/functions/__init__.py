"""SQL functions made of expressions, and a table function for textual patterns."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..pattern import PatternGraph


def register(spark: SparkSession) -> None:
    """signature(labels), same_multiset(a, b), cell_bitmap(positions) as session functions; they inline into plans."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION signature(labels ARRAY<STRING>) RETURNS ARRAY<STRING> RETURN sort_array(labels)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION same_multiset(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS BOOLEAN RETURN sort_array(a) = sort_array(b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_bitmap(positions ARRAY<INT>) RETURNS BIGINT RETURN aggregate(positions, 0L, (b, p) -> b | shiftleft(1L, p))")
    spark.udtf.register("pattern_edges", PatternEdges)


def parse(spec: str) -> PatternGraph:
    """'a:A b:B; b c:A': edges parted by ';', vertices by spaces, a label after ':' where a vertex first stands."""
    labels: dict = {}
    edges = []
    for part in spec.split(";"):
        edge = []
        for token in part.split():
            v, _, label = token.partition(":")
            if label or v not in labels:
                labels[v] = label
            edge.append(v)
        edges.append(edge)
    return PatternGraph.of(edges, labels)


@udtf(returnType="q: int, v: string, label: string")
class PatternEdges:
    """Rows of a textual pattern."""

    def eval(self, spec: str):
        p = parse(spec)
        for q, e in enumerate(p.edges):
            for v in e:
                yield q, v, p.label[v]
