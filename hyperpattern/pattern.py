"""The query hypergraph: small, immutable, on the driver."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property
from itertools import combinations

from pyspark.sql import DataFrame

MOST_EDGES = 62


@dataclass(frozen=True)
class PatternGraph:
    """edges: vertex tuples; labels: of each vertex; elabels: of each edge or None."""

    edges: tuple[tuple, ...]
    labels: tuple[tuple, ...]  # (vertex, label) pairs
    elabels: tuple = ()

    @classmethod
    def of(cls, edges, labels: dict, elabels=()) -> PatternGraph:
        edges = tuple(tuple(sorted(set(e), key=str)) for e in edges)
        if not 0 < len(edges) <= MOST_EDGES:
            raise ValueError(f"a pattern has 1 to {MOST_EDGES} hyperedges")
        if any(not e for e in edges):
            raise ValueError("a hyperedge has at least one vertex")
        used = {v for e in edges for v in e}
        return cls(edges, tuple(sorted(((v, str(labels[v])) for v in used), key=str)), tuple(elabels))

    @classmethod
    def from_edges(cls, edges: DataFrame, ids: list) -> PatternGraph:
        """The pattern made of these edges of a data hypergraph, in the order of ids."""
        rows = {r["e"]: r for r in edges.where(edges["e"].isin(list(ids))).collect()}
        labels = {m["v"]: m["l"] for r in rows.values() for m in r["members"]}
        named = [rows[i]["elabel"] for i in ids]
        return cls.of([[m["v"] for m in rows[i]["members"]] for i in ids], labels, named if any(x is not None for x in named) else ())

    @cached_property
    def label(self) -> dict:
        return dict(self.labels)

    @property
    def size(self) -> int:
        return len(self.edges)

    @property
    def full(self) -> int:
        return (1 << self.size) - 1

    def signature(self, vertices) -> list[str]:
        return sorted(self.label[v] for v in vertices)

    @cached_property
    def overlaps(self) -> dict[tuple[int, int], list[str]]:
        """Signature of the shared vertices of each adjacent pair q < q2."""
        return {(a, b): self.signature(s) for a, b in combinations(range(self.size), 2) if (s := set(self.edges[a]) & set(self.edges[b]))}

    @cached_property
    def adjacent(self) -> list[int]:
        """For each edge, the bitmap of its adjacent edges."""
        out = [0] * self.size
        for a, b in self.overlaps:
            out[a] |= 1 << b
            out[b] |= 1 << a
        return out

    @cached_property
    def bitmaps(self) -> dict:
        """For each vertex, the bitmap of the edges it lies in."""
        return {v: sum(1 << q for q, e in enumerate(self.edges) if v in e) for v in self.label}

    def cells(self, q: int, mask: int) -> list[tuple[int, str]]:
        """The cells of edge q's vertices when the edges in mask and q are mapped, sorted."""
        return sorted((self.bitmaps[u] & (mask | 1 << q), self.label[u]) for u in self.edges[q])

    def induced(self, mask: int) -> PatternGraph:
        keep = [q for q in range(self.size) if mask >> q & 1]
        return PatternGraph.of([self.edges[q] for q in keep], self.label, [self.elabels[q] for q in keep] if self.elabels else ())

    def components(self) -> list[list[int]]:
        left, out = set(range(self.size)), []
        while left:
            todo, part = [min(left)], set()
            while todo:
                q = todo.pop()
                if q in part:
                    continue
                part.add(q)
                todo += [x for x in range(self.size) if self.adjacent[q] >> x & 1]
            out.append(sorted(part))
            left -= part
        return out

    def subsets(self):
        """Non-empty subsets of edges with the signature of their common vertices."""
        for n in range(1, self.size + 1):
            for s in combinations(range(self.size), n):
                yield s, self.signature(set.intersection(*(set(self.edges[q]) for q in s)))
