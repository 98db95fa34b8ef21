"""Depth-first interleaved search on executors, for a pruned candidate space small enough that each holds all of it."""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame

from .candidates import CandidateSpace
from .pattern import PatternGraph


class Searcher:
    def __init__(self, p: PatternGraph, members: dict, links: dict, order: str, prune: str, non_simple: bool):
        self.p, self.members, self.links, self.order, self.non_simple = p, members, links, order, non_simple
        self.by_connection, self.by_cells = prune in ("connectivity", "both"), prune in ("intersection", "both")
        self.bitmaps: Counter = Counter()
        self.checks = self.extended = self.dead = 0

    def choose(self, live: dict[int, list], mask: int) -> int:
        near = self.p.adjacent
        key = {
            "dynamic": lambda q: (len(live[q]) != 1, -(near[q] & ~mask).bit_count(), len(live[q]), q),
            "degree": lambda q: (-near[q].bit_count(), q),
            "candsize": lambda q: (len(live[q]), q),
            "constraints": lambda q: (-(near[q] & mask).bit_count(), q),
            "fixed": lambda q: q,
            "random": lambda q: (int(hashlib.md5(str(q).encode()).hexdigest()[:8], 16), q),
        }[self.order]
        return min(live, key=key)

    def fits(self, q: int, f, mask: int) -> bool:
        self.checks += 1
        bit = 1 << q
        return sorted((self.bitmaps[v] | bit, x) for v, x in self.members[f]) == self.p.cells(q, mask)

    def pruned(self, live: dict[int, list], last: int, used, mask: int) -> dict[int, list] | None:
        out = {}
        for q, fs in live.items():
            if q == last:
                continue
            if self.by_connection and self.p.adjacent[last] >> q & 1:
                reach = self.links.get((last, used, q), ())
                fs = [f for f in fs if f in reach]
            if self.by_cells:
                fs = [f for f in fs if self.fits(q, f, mask)]
            if not fs:
                self.dead += 1
                return None
            out[q] = fs
        return out

    def search(self, live: dict[int, list], chosen: dict, only=None) -> Iterator[tuple]:
        mask = sum(1 << q for q in chosen)
        q = self.choose(live, mask)
        for f in live[q] if only is None else [only]:
            if self.non_simple and f in chosen.values() or not self.by_cells and not self.fits(q, f, mask):
                continue
            self.extended += 1
            found = {**chosen, q: f}
            if len(found) == self.p.size:
                yield tuple(found[i] for i in range(self.p.size))
                continue
            for v, _ in self.members[f]:
                self.bitmaps[v] |= 1 << q
            rest = self.pruned(live, q, f, mask | 1 << q)
            if rest is not None:
                yield from self.search(rest, found)
            for v, _ in self.members[f]:
                self.bitmaps[v] &= ~(1 << q)


def gathered(space: CandidateSpace) -> tuple[dict[int, list], dict, dict]:
    """The space as dictionaries; the caller has checked its size."""
    live: dict[int, list] = {}
    members: dict = {}
    for r in space.candidates.orderBy("q", "f").collect():
        live.setdefault(r["q"], []).append(r["f"])
        members[r["f"]] = [(m["v"], m["l"]) for m in r["members"]]
    links: dict = {}
    for r in space.connections.collect():
        links.setdefault((r["q"], r["f"], r["q2"]), set()).add(r["f2"])
    return live, members, links


def match_local(p: PatternGraph, space: CandidateSpace, order: str = "dynamic", prune: str = "both", non_simple: bool = False, limit: int | None = None) -> DataFrame:
    spark = space.candidates.sparkSession
    live, members, links = gathered(space)
    kind = dict(space.candidates.dtypes)["f"]
    schema = ", ".join(f"m{q} {kind}" for q in range(p.size))
    if len(live) < p.size:
        return spark.createDataFrame([], schema)
    first = Searcher(p, members, links, order, prune, non_simple).choose(live, 0)
    shared = spark.sparkContext.broadcast((p, live, members, links))
    names = [f"m{q}" for q in range(p.size)]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p, live, members, links = shared.value
        made = 0
        for frame in frames:
            for seed in frame["seed"]:
                rows = []
                for row in Searcher(p, members, links, order, prune, non_simple).search(live, {}, seed):
                    rows.append(row)
                    made += 1
                    if len(rows) == 10_000 or made == limit:
                        yield pd.DataFrame(rows, columns=names)
                        rows = []
                    if made == limit:
                        return
                if rows:
                    yield pd.DataFrame(rows, columns=names)

    seeds = spark.createDataFrame([(f,) for f in live[first]], f"seed {kind}")
    parts = min(len(live[first]), int(spark.conf.get("spark.sql.shuffle.partitions")))
    return seeds.repartition(parts).mapInPandas(run, schema)
