"""BIPARTITE: both hypergraphs become graphs of vertex nodes and edge nodes, and a subgraph matching finds the pattern's graph."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import HypergraphFrame
from ..order import static_order
from ..pattern import PatternGraph
from ..storage import held

#: Pairs in a tile of a join, and edges of a vertex that travel in one list.
PAIRS, LISTED = 1 << 21, 1 << 16


def transform(h: HypergraphFrame, edge_node_label: str = "arity") -> tuple[DataFrame, DataFrame]:
    """(nodes: id, label; arcs: a (vertex node), b (edge node)). edge_node_label: signature, arity or none.

    Without arity or signature an edge node also stands for larger edges, so results are too many; none shows that.
    """
    label = {"signature": F.concat(F.lit("E:"), F.array_join("sig", "|")), "arity": F.concat(F.lit("E:"), F.col("arity")), "none": F.lit("E:")}[edge_node_label]
    edge = F.concat(F.lit("e"), F.col("e").cast("string"))
    vertex = F.concat(F.lit("v"), F.col("v").cast("string"))
    nodes = h.edges.select(edge.alias("id"), label.alias("label")).unionByName(h.incidence().select(vertex.alias("id"), F.concat(F.lit("V:"), F.col("label")).alias("label")).distinct())
    return nodes, h.incidence().select(vertex.alias("a"), edge.alias("b"))


def labelled_arcs(h: HypergraphFrame, edge_node_label: str = "arity") -> DataFrame:
    """a, b, la, lb: the incidence graph's arcs with the labels of both ends; what a query needs of the transformed data."""
    nodes, arcs = (held(x, "graph") for x in transform(h, edge_node_label))
    return held(arcs.join(nodes.select(F.col("id").alias("a"), F.col("label").alias("la")), "a").join(nodes.select(F.col("id").alias("b"), F.col("label").alias("lb")), "b"), "arcs")


def match(h: HypergraphFrame, p: PatternGraph, edge_node_label: str = "arity", arc: DataFrame | None = None) -> DataFrame:
    """Edge nodes are met along a spanning order, each through a vertex node next to it and to an earlier one; nodes of one kind are all different. arc: labelled_arcs(h, edge_node_label), if they are there already.

    Pattern vertices of one label and the same edges are interchangeable, so no row is made for a choice among them. What they
    ask is counted: that an edge node has enough neighbours of each label, and that the vertex nodes next to the edge nodes so
    far, told apart by which of these they touch, are enough for all pattern vertices at once.
    """
    tag = {"signature": lambda e: "E:" + "|".join(p.signature(e)), "arity": lambda e: f"E:{len(e)}", "none": lambda e: "E:"}[edge_node_label]
    arc = labelled_arcs(h, edge_node_label) if arc is None else arc
    tags, wanted = [tag(e) for e in p.edges], [Counter(p.label[u] for u in e) for e in p.edges]
    number = F.substring("b", 2, 10**6).cast(dict(h.edges.dtypes)["e"])
    arcs = lambda q, label: arc.where((F.col("la") == f"V:{label}") & (F.col("lb") == tags[q])).select(number.alias(f"m{q}"), F.col("a").alias("_v"))
    fit = [_fitting(arc, number, tags[q], wanted[q]).withColumnRenamed("_e", f"m{q}") for q in range(p.size)]
    sizes = [0] * p.size
    if p.size > 2:
        found = held(reduce(DataFrame.unionByName, [x.select(F.lit(q).alias("q"), F.col(f"m{q}").alias("_e")) for q, x in enumerate(fit)]), "bipartite")
        have = {r["q"]: r["n"] for r in found.groupBy("q").agg(F.count("*").alias("n")).collect()}
        sizes = [have.get(q, 0) for q in range(p.size)]
        fit = [found.where(F.col("q") == q).select(F.col("_e").alias(f"m{q}")) for q in range(p.size)]
    order = static_order(p, sizes)
    rows = fit[order[0]]
    for n, q in enumerate(order[1:], 1):
        names = [f"m{i}" for i in order[:n]]
        shared = [(wanted[b][x] * wanted[q][x], i, x) for i, b in enumerate(order[:n]) for x in p.overlaps.get((min(b, q), max(b, q)), ())]
        through = None
        if shared:
            _, i, label = min(shared)
            through = (label, 1 << order[i] | 1 << q)
            side = arcs(q, label).join(fit[q], f"m{q}", "left_semi")  # edges without enough of a label go before they meet anything
            rows = _met(rows.join(arcs(order[i], label), f"m{order[i]}"), side, "_v", names, f"m{q}")
        else:
            rows = rows.crossJoin(fit[q]).where(~F.col(f"m{q}").isin(*[F.col(c) for c in names]))
        need = _uncounted(p, order[:n], q, through)
        if need:
            near = arc.where(F.col("la").isin([f"V:{x}" for x in need]) & F.col("lb").isin(sorted({tags[i] for i in order[: n + 1]}))).select(number.alias("_e"), "la", "a")
            rows = _seated(rows, near, order[: n + 1], need, edge_node_label != "none")
        if n < p.size - 1:
            rows = held(rows, "bipartite")
    return rows.select(*[f"m{q}" for q in range(p.size)])


def _fitting(arc: DataFrame, number: Column, tag: str, wanted: Counter) -> DataFrame:
    """_e: edge nodes of this label that have at least so many neighbours of each label."""
    enough = F.element_at(F.create_map(*[F.lit(x) for label, n in sorted(wanted.items()) for x in (f"V:{label}", n)]), F.col("la"))
    near = arc.where((F.col("lb") == tag) & F.col("la").isin([f"V:{x}" for x in sorted(wanted)])).groupBy(number.alias("_e"), "la").agg(F.count("*").alias("_n"))
    return near.where(F.col("_n") >= enough).groupBy("_e").agg(F.count("*").alias("_n")).where(F.col("_n") == len(wanted)).select("_e")


def _uncounted(p: PatternGraph, before: list[int], q: int, through: tuple[str, int] | None) -> dict[str, dict[int, int]]:
    """For each label of edge q, the pattern vertices of it by the mapped edges they lie in (bitmap: number); without labels whose vertices lie in one edge only, or are the one that q was met through."""
    mask, out = sum(1 << i for i in [*before, q]), {}
    for label in sorted({p.label[u] for u in p.edges[q]}):
        need = Counter(p.bitmaps[u] & mask for u, x in p.labels if x == label and p.bitmaps[u] & mask)
        if not (len(need) == 1 and (next(iter(need)).bit_count() == 1 or through and need == {through[1]: 1} and label == through[0])):
            out[label] = dict(need)
    return out


def _seated(rows: DataFrame, near: DataFrame, mapped: list[int], need: dict[str, dict[int, int]], exact: bool) -> DataFrame:
    """Rows whose edge nodes have distinct neighbours for all pattern vertices in `need`. near: _e, la, a.

    exact: an edge node has no more neighbours than the pattern's, so a vertex node touches just the edges its pattern
    vertex lies in, and the numbers must be equal. Else it may touch more, and the numbers are put to seats().
    """
    names = [f"m{i}" for i in mapped]
    each = F.explode(F.array(*[F.struct(F.lit(1 << i).cast("long").alias("bit"), F.col(f"m{i}").alias("e")) for i in mapped]))
    touched = rows.select(*names, each.alias("_x")).select(*names, F.col("_x.bit").alias("_bit"), F.col("_x.e").alias("_e")).join(near, "_e")
    vertices = touched.select(*names, "la", "a", "_bit").repartition(*names).groupBy(*names, "la", "a").agg(F.bit_or("_bit").alias("_bits"))
    cells = vertices.groupBy(*names, "la", "_bits").agg(F.count("*").alias("_n"))
    if exact:
        wanted = {f"{bits}:V:{label}": n for label, by in need.items() for bits, n in by.items()}
        known = F.element_at(F.create_map(*[F.lit(x) for kv in wanted.items() for x in kv]), F.concat_ws(":", "_bits", "la"))
        return cells.where(F.col("_n") == known).groupBy(*names).agg(F.count("*").alias("_n")).where(F.col("_n") == len(wanted)).select(*names)
    at = F.element_at(F.create_map(*[F.lit(x) for i, label in enumerate(need) for x in (f"V:{label}", i)]), F.col("la"))
    found = cells.groupBy(*names).agg(F.array_join(F.sort_array(F.collect_list(F.concat_ws(":", at, "_bits", "_n"))), ",").alias("_cells"))
    classes = list(need.values())

    def keep(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known: dict[str, bool] = {}
        for frame in frames:
            for text in set(frame["_cells"]) - known.keys():
                by: list[dict[int, int]] = [{} for _ in classes]
                for i, bits, n in (map(int, x.split(":")) for x in text.split(",")):
                    by[i][bits] = n
                known[text] = all(map(seats, classes, by))
            yield frame.loc[frame["_cells"].map(known).astype(bool), names]

    return found.mapInPandas(keep, rows.select(*names).schema)


def seats(need: dict[int, int], cells: dict[int, int]) -> bool:
    """Whether vertices (their bitmaps: number) are enough for pattern vertices (bitmaps: number), each taking one whose bitmap has all its bits: a flow by classes."""
    free, given = Counter(cells), Counter()
    for b, n in need.items():
        while n:
            came, via, todo, end = {}, {}, [b], None  # the class a cell is reached from, the cell a class is reached through
            for x in todo:
                for c in cells:
                    if c & x == x and c not in came:
                        came[c] = x
                        if free[c]:
                            end = c
                            break
                        for y in need:
                            if given[y, c] and y != b and y not in via:
                                via[y] = c
                                todo.append(y)
                if end is not None:
                    break
            if end is None:
                return False
            path, c = [], end
            while True:
                path.append((came[c], c))
                if came[c] == b:
                    break
                c = via[came[c]]
            moved = min(n, free[end], *[given[x, via[x]] for x, _ in path[:-1]])
            free[end] -= moved
            n -= moved
            for x, c in path:
                given[x, c] += moved
                if x != b:
                    given[x, via[x]] -= moved
    return True


def _met(rows: DataFrame, side: DataFrame, v: str, others: list[str], e: str) -> DataFrame:
    """Distinct (others, e) of rows (others, v, ...) and side (v, e), e unlike all others, without a shuffle of the pairs that vertices make.

    Rows are dealt to tiles by their edges. A vertex's edges travel once to every tile that has rows with it, in lists of
    bounded length, and pairs are made where they are told apart.
    """
    rows = rows.select(*others, v).distinct() if len(rows.columns) > len(others) + 1 else rows
    degree = side.groupBy(v).agg(F.count("*").alias("_n"))
    made, most = rows.groupBy(v).agg(F.count("*").alias("_m")).join(degree, v).agg(F.coalesce(F.sum(F.col("_m") * F.col("_n")), F.lit(0)), F.coalesce(F.max("_n"), F.lit(0))).first()
    tiles, lists = max(1, made // PAIRS), max(1, most // LISTED)
    dealt = rows.groupBy(v, F.pmod(F.xxhash64(*others), F.lit(tiles)).alias("_tile")).agg(F.collect_list(F.struct(*others)).alias("_rows"))
    edges = side.groupBy(v, F.pmod(F.xxhash64(e), F.lit(lists)).alias("_list")).agg(F.sort_array(F.collect_list(e)).alias("_edges"))
    met = dealt.join(edges, v).select("_tile", "_rows", "_edges").repartition(tiles, "_tile")
    met = met.select("_tile", F.explode("_rows").alias("_row"), "_edges").select("_tile", *[F.col(f"_row.{c}").alias(c) for c in others], F.explode("_edges").alias(e))
    return met.where(~F.col(e).isin(*[F.col(c) for c in others])).dropDuplicates(["_tile", *others, e]).drop("_tile")
