"""The experiments on the given tables. Each returns a table of runs or measures; walks, sizes and limits are parameters."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession

from . import walks
from .baselines import BASELINES, INDEXES
from .baselines.bipartite import transform
from .baselines.profile import index
from .candidates import build_space, prune_to_fixpoint
from .carriers import NAMES, hypergraph
from .localsearch import match_local
from .measures import SCHEMA, effort, effort_of_pairs, peak_bytes, space_stats, timed
from .model import HypergraphFrame
from .plans.choice import choose
from .search import PRUNES, match, wavefront
from .storage import forget, held

SIZES = (3, 6, 9, 12, 15)
SYSTEMS = ("interleaved", "bipartite", "profile", "overlap")


def _queries(h: HypergraphFrame, size: int, n: int, seed: int) -> dict:
    return walks.patterns(h, walks.sample(h, size, n, seed))


def query_times(spark: SparkSession, sf_dir: str, names=("supply_region", "coactive_10m"), sizes=SIZES, n: int = 30, systems=SYSTEMS, time_limit: float = 600.0, seed: int = 0) -> DataFrame:
    """Time and embeddings by hypergraph, size, query and system."""
    rows = []
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        given = {s: {INDEXES[s][0]: INDEXES[s][1](h)} for s in systems if s in INDEXES}  # indexes are no part of a query's time
        for size in sizes:
            for q, p in _queries(h, size, n, seed).items():
                for system in systems:
                    run = (lambda: match(h, p).count()) if system == "interleaved" else (lambda: BASELINES[system](h, p, **given.get(system, {})).count())  # noqa: B023
                    seconds, solved, found, group = timed(spark, run, time_limit)
                    rows.append((name, system, size, str(q), seconds, solved, found, peak_bytes(spark, group)))
    return spark.createDataFrame(rows, SCHEMA)


def filter_shares(spark: SparkSession, sf_dir: str, names=("customer_parts", "basket_type"), size: int = 3, n: int = 2, seed: int = 0) -> DataFrame:
    """Seconds of a query by stage: candidates and connections, initial filter, search; and the first two's share."""
    rows = []
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        for q, p in _queries(h, size, n, seed).items():
            t0 = time.monotonic()
            space = build_space(p, h)
            t1 = time.monotonic()
            space = prune_to_fixpoint(p, space)
            t2 = time.monotonic()
            found = (match_local(p, space) if choose(space) == "local" else wavefront(p, space)).count()
            t3 = time.monotonic()
            rows.append((name, str(q), t1 - t0, t2 - t1, t3 - t2, (t2 - t0) / (t3 - t0), found))
    return spark.createDataFrame(rows, "hypergraph string, query_id string, space_seconds double, filter_seconds double, search_seconds double, filter_share double, embeddings long")


def candidate_spaces(spark: SparkSession, sf_dir: str, names=("basket_type", "supply_region", "coactive_10m"), sizes=(3, 6), n: int = 5, seed: int = 0) -> DataFrame:
    """Candidates and connections before and after the initial filter."""
    rows = []
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        for size in sizes:
            for q, p in _queries(h, size, n, seed).items():
                rows.append({"hypergraph": name, "size": size, "query_id": str(q), **space_stats(p, h)})
    return spark.createDataFrame(rows)


def pruning_ablation(spark: SparkSession, sf_dir: str, names=("coactive_10m",), size: int = 4, n: int = 5, seed: int = 0) -> DataFrame:
    """Search effort by pruning variant, and without the initial filter."""
    rows = []
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        for q, p in _queries(h, size, n, seed).items():
            raw = build_space(p, h)
            kept = prune_to_fixpoint(p, raw)
            for variant, space, prune in [*((v, kept, v) for v in PRUNES), ("both, unfiltered", raw, "both")]:
                rows.append({"hypergraph": name, "size": size, "query_id": str(q), "variant": variant, **effort(p, space, prune=prune)})
    return spark.createDataFrame(rows)


def preprocessing(spark: SparkSession, sf_dir: str, names=("basket_type", "supply_region")) -> DataFrame:
    """Seconds to build what each system needs before queries: signature index, inverted index, incidence graph."""
    rows = []
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        for system, build in (("interleaved", lambda: held(h.edges.repartition("sig_id").sortWithinPartitions("sig_id"), "index")), ("profile", lambda: held(index(h), "inverted")), ("overlap", lambda: held(h.edges.repartition("sig_id"), "index")), ("bipartite", lambda: [held(x, "graph") for x in transform(h)])):  # noqa: B023
            t = time.monotonic()
            build()
            rows.append((name, system, time.monotonic() - t))
    return spark.createDataFrame(rows, "hypergraph string, system string, seconds double")


def dataset_statistics(spark: SparkSession, sf_dir: str, names=NAMES) -> DataFrame:
    """One row for each hypergraph. They are made one after the other, and each is removed before the next."""
    rows, schema = [], None
    for name in names:
        h = hypergraph(spark, sf_dir, name).materialise()
        one = h.stats()
        rows.append((name, *one.first()))
        schema = one.schema
        forget(h.edges)
    return spark.createDataFrame(rows, "hypergraph string, " + ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in schema))


def verification_times(spark: SparkSession, sf_dir: str, name: str = "supply_region", size: int = 4, n: int = 3, seed: int = 0) -> DataFrame:
    """Seconds that three exact tests take on the same rows: every pair of connected candidates of each query, put to the cell check, the vertex profiles and the intersections of all subsets."""
    from pyspark.sql import functions as F

    from .baselines.profile import profiles, query_profiles
    from .cells import cell_check, extended_cells, subset_test

    h = hypergraph(spark, sf_dir, name).materialise()
    rows = []
    for q, p in _queries(h, size, n, seed).items():
        a, b = next(iter(p.overlaps))
        two = p.induced(1 << a | 1 << b)
        space = build_space(two, h)
        side = lambda i: space.candidates.where(F.col("q") == i).select(F.col("f").alias(f"m{i}"), F.col("members").alias(f"x{i}"))  # noqa: E731, B023
        pairs = held(side(0).crossJoin(side(1)).where("m0 <> m1"), "pairs")
        vertex = pairs.schema["x0"].dataType.elementType["v"].dataType.simpleString()
        empty = F.create_map().cast(f"map<{vertex},bigint>")
        x0, x1 = F.col("x0"), F.col("x1")
        tests = {
            "cells": cell_check(two, x1, extended_cells(x0, empty, F.lit(0)), F.lit(1), F.lit(1).cast("long")),
            "profiles": profiles([x0, x1]) == query_profiles(two, [0, 1]),
            "intersections": subset_test(two, [x0, x1]),
        }
        for kind, test in tests.items():
            t = time.monotonic()
            kept = pairs.where(test).count()
            rows.append((name, kind, str(q), pairs.count(), kept, time.monotonic() - t))
    return spark.createDataFrame(rows, "hypergraph string, test string, query_id string, checked long, kept long, seconds double")


def unlabelled_difficulty(spark: SparkSession, sf_dir: str, size: int = 2, n: int = 2, seed: int = 0, most: int | None = 50_000) -> DataFrame:
    """The same walks over the same edges with and without labels: candidates, connections, embeddings (up to `most`) and cell checks; truncated: the search ended at `most`, so the row's costs are lower bounds.

    most None: walks of two edges are searched to the end, in tables; with a limit, or more edges, the space is gathered on the driver.
    """
    if most is None and size != 2:
        raise ValueError("larger walks need a limit")
    rows = []
    labelled, plain = (hypergraph(spark, sf_dir, x).materialise() for x in ("basket_type", "basket_plain"))
    w = walks.sample(labelled, size, n, seed)
    for name, h in (("basket_type", labelled), ("basket_plain", plain)):
        for q, p in walks.patterns(h, w).items():
            space = prune_to_fixpoint(p, build_space(p, h))
            cost = effort_of_pairs(p, space) if most is None else effort(p, space, most=most)
            rows.append({"hypergraph": name, "query_id": str(q), "candidates": space.candidates.count(), "connections": space.connections.count() // 2, **cost, "truncated": cost["embeddings"] == most})
    return spark.createDataFrame(rows)
