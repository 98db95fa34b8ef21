"""Interleaved search: partial embeddings are extended in rounds, and every round prunes what each of them may still use.

A partial embedding is a row of `front`: m (data edge of each query edge, null if unmapped), mask, cells (bitmap of each
data vertex). `live` (m, q, f) holds the candidates it has left. A round drops dead ends, lets each row choose its own
next query edge, extends it, and prunes the new rows' candidates by connections and by the cell check.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .candidates import CandidateSpace, build_space, prune_to_fixpoint
from .cells import cell_check, extended_cells
from .localsearch import match_local
from .model import HypergraphFrame
from .order import order_key
from .pattern import PatternGraph
from .plans.choice import choose
from .storage import held

#: Candidates of the first query edge that the wavefront starts from at once.
SEEDS = 100_000
PRUNES = {"none": (False, False), "connectivity": (True, False), "intersection": (False, True), "both": (True, True)}


def _bit(q: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), q)


def _wide(p: PatternGraph, rows: DataFrame) -> DataFrame:
    return rows.select(*[F.element_at("m", q + 1).alias(f"m{q}") for q in range(p.size)])


def wavefront(p: PatternGraph, space: CandidateSpace, order: str = "dynamic", prune: str = "both", non_simple: bool = False) -> DataFrame:
    """m0 .. mk-1 of all embeddings. prune: none, connectivity, intersection or both; all give the same rows.

    Where pruning leaves room for candidates that don't fit (anything but the intersection step), a chosen candidate is
    put to the cell check before its row is extended.
    """
    by_connection, by_cells = PRUNES[prune]
    c, k = space.candidates, space.connections
    kind = dict(c.dtypes)["f"]
    vertex = c.schema["members"].dataType.elementType["v"].dataType.simpleString()
    start = F.array(*[F.lit(None).cast(kind) for _ in range(p.size)])
    front = c.sparkSession.range(1).select(start.alias("m"), F.lit(0).cast("long").alias("mask"), F.create_map().cast(f"map<{vertex},bigint>").alias("cells"))
    live = c.select(start.alias("m"), "q", "f")
    for done in range(p.size):
        sizes = live.groupBy("m", "q").agg(F.count("*").alias("n")).join(front.select("m", "mask"), "m")
        chosen = sizes.groupBy("m", "mask").agg(F.bit_or(_bit(F.col("q"))).alias("have"), F.min_by("q", order_key(p, order, F.col("q"), F.col("n"), F.col("mask"))).alias("pick"))
        chosen = chosen.where(F.col("have") == F.lit(p.full).bitwiseAND(F.bitwise_not("mask"))).select("m", "pick")
        picked = live.join(chosen, "m").where("q = pick").select("m", "q", "f").join(front, "m").join(c, ["q", "f"])
        if not by_cells:
            picked = picked.where(cell_check(p, F.col("members"), F.col("cells"), F.col("q"), F.col("mask")))
        if non_simple:
            picked = picked.where(~F.coalesce(F.array_contains("m", F.col("f")), F.lit(False)))
        grown = F.transform("m", lambda x, i: F.when(i == F.col("q"), F.col("f")).otherwise(x))
        fresh = picked.select(
            F.col("m").alias("parent"),
            grown.alias("m"),
            F.col("mask").bitwiseOR(_bit(F.col("q"))).alias("mask"),
            extended_cells(F.col("members"), F.col("cells"), F.col("q")).alias("cells"),
            F.col("q").alias("last"),
            F.col("f").alias("with"),
        )
        fresh = held(fresh, "front")
        if done == p.size - 1 or fresh.isEmpty():
            return _wide(p, fresh)
        step = fresh.select("parent", "m", "last", "with", "mask")
        if by_connection:
            # beside the last edge, candidates come from its connections; the product with all that its parent had left is never made
            near = F.element_at(F.array(*[F.lit(a).cast("long") for a in p.adjacent]), F.col("last") + 1)
            linked = step.join(k.select("q", "f", F.col("q2").alias("last"), F.col("f2").alias("with")), ["last", "with"])
            if done:
                linked = linked.join(live.withColumnRenamed("m", "parent"), ["parent", "q", "f"], "left_semi")
            else:
                linked = linked.join(c.select("q", "f"), ["q", "f"], "left_semi")
            left = linked.select("m", "q", "f", "mask")
            apart = [(i, q) for i in range(p.size) for q in range(p.size) if i != q and not p.adjacent[i] >> q & 1]
            if apart:
                away = live.withColumnRenamed("m", "parent").where(F.col("q").isin(sorted({q for _, q in apart}))).join(step.where(F.col("last").isin(sorted({i for i, _ in apart}))), "parent")
                away = away.where((F.col("q") != F.col("last")) & (near.bitwiseAND(_bit(F.col("q"))) == 0))
                left = left.unionByName(away.select("m", "q", "f", "mask"))
        else:
            left = live.withColumnRenamed("m", "parent").join(step, "parent").where("q <> last").select("m", "q", "f", "mask")
        if by_cells:
            left = left.join(fresh.select("m", "cells"), "m").join(c, ["q", "f"]).where(cell_check(p, F.col("members"), F.col("cells"), F.col("q"), F.col("mask")))
        front, live = fresh.select("m", "mask", "cells"), held(left.select("m", "q", "f"), "live")
    return _wide(p, front)


def seed_batches(p: PatternGraph, space: CandidateSpace, order: str, batch: int) -> list[CandidateSpace]:
    """The space cut by its first query edge's candidates into parts of about `batch` seeds each, by hash; connections are left as they are."""
    c = space.candidates
    sizes = c.groupBy("q").agg(F.count("*").alias("n"))
    first = sizes.orderBy(order_key(p, order, F.col("q"), F.col("n"), F.lit(0).cast("long"))).first()
    parts = max(1, -(-first["n"] // batch))
    part = F.pmod(F.xxhash64("f"), F.lit(parts))
    return [CandidateSpace(c.where((F.col("q") != first["q"]) | (part == i)), space.connections) for i in range(parts)]


def wavefront_in_batches(p: PatternGraph, space: CandidateSpace, order: str = "dynamic", prune: str = "both", non_simple: bool = False, batch: int = SEEDS, limit: int | None = None) -> DataFrame:
    """The wavefront over one batch of seeds after the other, so that the frontier is bounded by what a batch grows to; no more batches are run once `limit` rows are found."""
    out, have = None, 0
    for part in seed_batches(p, space, order, batch):
        found = wavefront(p, part, order, prune, non_simple)
        out = found if out is None else out.unionByName(found)
        if limit is not None:
            have += found.limit(limit).count()
            if have >= limit:
                break
    return out


def match(h: HypergraphFrame, p: PatternGraph, order: str = "dynamic", prune: str = "both", engine: str = "auto", limit: int | None = None, initial_filter: bool = True, non_simple: bool = False, batch: int = SEEDS) -> DataFrame:
    """All embeddings of p in h, m0 .. mk-1. A pattern of several components is matched by component and combined where the parts are disjoint."""
    parts = p.components()
    if len(parts) > 1:
        return _combined(h, p, parts, order, prune, engine, limit, initial_filter, non_simple)
    space = build_space(p, h)
    if initial_filter:
        space = prune_to_fixpoint(p, space)
    present = space.candidates.select("q").distinct().count()
    if present < p.size:
        kind = dict(space.candidates.dtypes)["f"]
        return h.edges.sparkSession.createDataFrame([], ", ".join(f"m{q} {kind}" for q in range(p.size)))
    if engine == "auto":
        engine = choose(space)
    if engine == "local":
        out = match_local(p, space, order, prune, non_simple, limit)
    else:
        # with a limit the first batches are small, since few seeds may do
        out = wavefront_in_batches(p, space, order, prune, non_simple, batch if limit is None else min(batch, max(64, limit)), limit)
    return out if limit is None else out.limit(limit)


def _combined(h, p, parts, order, prune, engine, limit, initial_filter, non_simple) -> DataFrame:
    """Embeddings of the components side by side; no vertex may serve two of them."""
    out = None
    for part in parts:
        mask = sum(1 << q for q in part)
        found = match(h, p.induced(mask), order, prune, engine, None, initial_filter, non_simple)
        found = found.withColumnsRenamed({f"m{i}": f"_{q}" for i, q in enumerate(part)})
        used = found
        for q in part:
            used = used.join(h.edges.select(F.col("e").alias(f"_{q}"), F.transform("members", lambda x: x["v"]).alias(f"_v{q}")), f"_{q}")
        used = used.select(*[f"_{q}" for q in part], F.array_distinct(F.concat(*[f"_v{q}" for q in part])).alias("used"))
        if out is None:
            out = used
        else:
            both = out.withColumnRenamed("used", "before").crossJoin(used).where(~F.arrays_overlap("before", "used"))
            out = both.withColumn("used", F.concat("before", "used")).drop("before")
    out = out.select(*[F.col(f"_{q}").alias(f"m{q}") for q in range(p.size)])
    return out if limit is None else out.limit(limit)


def count_embeddings(h: HypergraphFrame, p: PatternGraph, **how) -> int:
    return match(h, p, **how).count()


def exists_embedding(h: HypergraphFrame, p: PatternGraph, **how) -> bool:
    return not match(h, p, limit=1, **how).isEmpty()


def embeddings_long(found: DataFrame) -> DataFrame:
    """embedding_id (edges joined by '|'), q, f."""
    return found.select(F.concat_ws("|", *found.columns).alias("embedding_id"), F.posexplode(F.array(*found.columns)).alias("q", "f"))


def distinct_subgraphs(found: DataFrame) -> DataFrame:
    """Embeddings that use the same data edges, whatever their order, once: edges (joined by '|')."""
    return found.select(F.array_join(F.sort_array(F.array(*found.columns)), "|").alias("edges")).distinct()


def witness(h: HypergraphFrame, p: PatternGraph, found: DataFrame) -> DataFrame:
    """m0 .. mk-1, u, v: one vertex mapping of each embedding. Vertices of a cell and label are matched by rank."""
    names = [f"m{q}" for q in range(p.size)]
    rows = found.select(*names, F.posexplode(F.array(*names)).alias("pos", "e")).join(h.edges.select("e", F.inline("members")), "e")
    bits = rows.groupBy(*names, "v", "l").agg(F.bit_or(_bit(F.col("pos"))).alias("b"))
    group = F.transform(F.sort_array(F.collect_list("v")), lambda x, i: F.struct(x.alias("v"), i.alias("r")))
    ranked = bits.groupBy(*names, "b", "l").agg(group.alias("g")).select(*names, "b", "l", F.inline("g"))
    seen: dict[tuple, int] = {}
    rows_q = []
    for v, label in p.labels:
        cell = (p.bitmaps[v], label)
        rows_q.append((str(v), *cell, seen.get(cell, 0)))
        seen[cell] = seen.get(cell, 0) + 1
    query = F.broadcast(h.edges.sparkSession.createDataFrame(rows_q, "u string, b long, l string, r int"))
    return ranked.join(query, ["b", "l", "r"]).select(*names, "u", "v")


def is_isomorphic(a: HypergraphFrame, b: HypergraphFrame, most: int = 62) -> bool:
    """Equal sizes and an embedding of a in b. ValueError if a has more than `most` edges (a bitmap has 62)."""
    left, right = a.stats().first(), b.stats().first()
    if left != right:
        return False
    ids = [r["e"] for r in a.edges.select("e").orderBy("e").limit(most + 1).collect()]
    return exists_embedding(b, PatternGraph.from_edges(a.edges, ids))


def estimate_count(h: HypergraphFrame, p: PatternGraph, one_in: int = 4, seed: int = 0) -> float:
    """Embeddings found from a hash-chosen part of the first edge's candidates, scaled up. An estimate by design."""
    space = prune_to_fixpoint(p, build_space(p, h))
    drawn = (F.col("q") != 0) | (F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "f")), 1, 8), 16, 10).cast("long"), F.lit(one_in)) == 0)
    some = CandidateSpace(held(space.candidates.where(drawn), "candidates"), space.connections)
    return float(wavefront(p, some).count() * one_in)
