"""What larger tables met: long plans, products and sums that need no pairs."""

import itertools
import random
from importlib import import_module

import pytest
from pyspark.sql import functions as F

from hyperpattern import adjacency, measures, search, workloads
from hyperpattern.baselines import BASELINES
from hyperpattern.candidates import build_space, prune_to_fixpoint
from hyperpattern.model import HypergraphFrame
from hyperpattern.operators import interval_counts, interval_join
from hyperpattern.pattern import PatternGraph


def graph(spark, data, label):
    return HypergraphFrame.from_incidence(spark.createDataFrame([(e, v, label[v]) for e, vs in data.items() for v in vs], "e long, v long, label string")).materialise()


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_bipartite_takes_edges_of_many_vertices(spark):
    """72 joins in one plan, and every order of equally labelled vertices, were too much."""
    data = {0: range(24), 1: range(20, 44), 2: range(40, 64), 3: range(21, 45)}
    label = {v: "ABCDE"[v % 5] for v in range(64)}
    p = PatternGraph.of([data[0], data[1], data[2]], label)
    assert rows(BASELINES["bipartite"](graph(spark, data, label), p)) == [(0, 1, 2), (2, 1, 0)]  # the middle edge is alike on both sides


def test_interchangeable_vertices_are_taken_in_one_order(spark):
    data = {0: [1, 2, 3], 1: [3, 4], 2: [1, 2, 4], 3: [2, 3]}
    label = {1: "A", 2: "A", 3: "B", 4: "B"}
    h = graph(spark, data, label)
    p = PatternGraph.of([["x", "y", "z"], ["z", "w"]], {"x": "A", "y": "A", "z": "B", "w": "B"})
    want = sorted({(e, f) for e in data for f in data if e != f for x, y in itertools.permutations(data[e], 2) for z in set(data[e]) & set(data[f]) for w in data[f] if len({x, y, z, w}) == 4 and [label[i] for i in (x, y, z, w)] == ["A", "A", "B", "B"]})
    assert rows(BASELINES["bipartite"](h, p, "none")) == want == [(0, 1), (2, 1)]


def test_bipartite_makes_no_row_for_a_vertex_that_only_has_to_exist(spark):
    """F8: an edge with 300 vertices of a label made 300 rows for each pattern vertex of it."""
    data = {0: [*range(300), 1000], 1: [1000, *range(2000, 2300)]}
    label = {v: "A" if v < 1000 else "B" if v == 1000 else "C" for vs in data.values() for v in vs}
    found = BASELINES["bipartite"](graph(spark, data, label), PatternGraph.of([["a", "b"], ["b", "c"]], {"a": "A", "b": "B", "c": "C"}), "none")
    assert rows(found) == [(0, 1)]
    assert "count(1)" in found._jdf.queryExecution().toString()  # existence is counted by edge


def test_the_last_edge_is_met_in_tiles(spark, monkeypatch):
    """F8: pairs of edges that share a vertex were shuffled, before the edges without a needed label had gone."""
    data = {e: [v for v in range(40) if (e * 7 + v * 11) % 5 == 0] + [100 + e % 7] for e in range(60)}
    label = {v: "B" if v < 40 else "AC"[v % 2] for vs in data.values() for v in vs}
    bipartite = import_module("hyperpattern.baselines.bipartite")
    monkeypatch.setattr(bipartite, "PAIRS", 500)
    monkeypatch.setattr(bipartite, "LISTED", 3)
    found = BASELINES["bipartite"](graph(spark, data, label), PatternGraph.of([["a", "b"], ["b", "c"]], {"a": "A", "b": "B", "c": "C"}), "none")
    has = lambda e, y: any(label[v] == y for v in data[e])
    want = sorted((e, f) for e in data for f in data if e != f and has(e, "A") and has(f, "C") and any(label[v] == "B" for v in set(data[e]) & set(data[f])))
    assert rows(found) == want != []
    plan = found._jdf.queryExecution().executedPlan().toString()
    after = plan[: plan.index("Generate explode")]  # from the pairs on to the result
    assert "Exchange" not in after and "_tile" in after


def test_bipartite_makes_no_choice_among_equal_vertices(spark):
    """30 vertices of a label that also occurs in other edges made a row for every ascending choice of them."""
    data = {0: range(60), 1: range(58, 118), 2: range(116, 176), 3: range(56, 116)}
    h = graph(spark, data, {v: "AB"[v % 2] for v in range(176)})
    p = PatternGraph.of([data[0], data[1], data[2]], {v: "AB"[v % 2] for v in range(176)})
    _, solved, found, _ = measures.timed(spark, lambda: rows(BASELINES["bipartite"](h, p)), 60)
    assert solved
    assert found == [(0, 1, 2), (2, 1, 0)]


@pytest.mark.parametrize("seed", range(3))
def test_bipartite_without_arity_finds_what_some_mapping_makes(spark, seed):
    r = random.Random(seed)
    label = {v: r.choice("AB") for v in range(7)}
    data = {e: r.sample(range(7), r.randint(2, 5)) for e in range(8)}
    name = {u: label[u] for u in range(5)}
    p = PatternGraph.of([r.sample(range(5), r.randint(2, 3)) for _ in range(2 + seed % 2)], name)
    want = set()
    for image in itertools.permutations(label, len(p.label)):
        phi = dict(zip(p.label, image, strict=True))
        if all(label[v] == p.label[u] for u, v in phi.items()):
            near = [[f for f in data if {phi[u] for u in e} <= set(data[f])] for e in p.edges]
            want |= {found for found in itertools.product(*near) if len(set(found)) == p.size}
    assert rows(BASELINES["bipartite"](graph(spark, data, label), p, "none")) == sorted(want) != []


def test_seats_are_those_of_some_assignment():
    seats = import_module("hyperpattern.baselines.bipartite").seats
    r, seen = random.Random(0), set()
    for _ in range(300):
        need = {b: r.randint(1, 2) for b in r.sample(range(1, 8), r.randint(1, 4))}
        cells = {c: r.randint(1, 2) for c in r.sample(range(1, 8), r.randint(1, 4))}
        us, vs = [b for b, n in need.items() for _ in range(n)], [c for c, n in cells.items() for _ in range(n)]

        def placed(i, left):
            return i == len(us) or any(c & us[i] == us[i] and placed(i + 1, left[:j] + left[j + 1 :]) for j, c in enumerate(left))

        assert seats(need, cells) == placed(0, vs)
        seen.add(seats(need, cells))
    assert seen == {True, False}


def test_the_inverted_index_holds_no_signature(spark, monkeypatch):
    """each of an edge's rows held the edge's signature, so the index grew with the square of an edge. Signatures of one hash are told apart all the same."""
    data = {0: [1, 2], 1: [2, 3], 2: [2, 4], 3: [1, 2, 3]}
    label = {1: "A", 2: "B", 3: "C", 4: "D"}
    h = graph(spark, data, label)
    p = PatternGraph.of([["x", "y"], ["y", "z"]], {"x": "A", "y": "B", "z": "C"})
    profile = import_module("hyperpattern.baselines.profile")
    assert dict(profile.index(h).dtypes) == {"v": "bigint", "sig_id": "bigint", "e": "bigint"}
    monkeypatch.setattr(profile, "signature_hash", lambda labels: 7)
    assert rows(BASELINES["profile"](HypergraphFrame(h.edges.withColumn("sig_id", F.lit(7).cast("long"))), p)) == [(0, 1)]


def test_interval_counts_equal_the_pairs(spark):
    """spans and points of one bucket met in pairs."""
    points = spark.createDataFrame([(i, (i * 7919) % 5000 if i % 50 else None) for i in range(400)] + [(7, 10), (7, 10)], "id int, t long")
    spans = spark.createDataFrame([((i * 31) % 5000, (i * 31) % 5000 + i % 700 - 5) for i in range(300)] + [(None, 9), (9, None)], "lo long, hi long")
    got = interval_counts(points, "t", spans, "lo", "hi", 640).groupBy("id").agg(F.sum("n_spans").alias("n"))
    pairs = interval_join(points, "t", spans.where("lo < hi"), "lo", "hi", 640).groupBy("id").agg(F.count("*").alias("n"))
    assert rows(got) == rows(pairs) != []
    plan = interval_counts(points, "t", spans, "lo", "hi", 640)._jdf.queryExecution().executedPlan().toString()
    assert "_bucket" in plan and "t#" in plan and "BroadcastNestedLoopJoin" not in plan


def test_the_wavefront_makes_no_product_beside_the_last_edge(spark, monkeypatch):
    """every new row met all that its parent had left, before connections were looked at."""
    data = {0: [1, 2], 1: [2, 3], 2: [3, 1, 4], 3: [1, 5], 4: [5, 3], 5: [3, 6]}
    label = {1: "A", 2: "B", 3: "C", 4: "D", 5: "B", 6: "B"}
    p = PatternGraph.of([["a", "b"], ["b", "c"], ["c", "a", "d"]], dict(zip("abcd", "ABCD", strict=True)))
    plans = []
    plain = search.held
    monkeypatch.setattr(search, "held", lambda df, name: (plans.append((name, df._jdf.queryExecution().optimizedPlan().toString())), plain(df, name))[1])
    assert rows(search.match(graph(spark, data, label), p, engine="wavefront")) == [(0, 1, 2), (3, 4, 2)]
    joins = [x for name, plan in plans if name == "live" for x in plan.splitlines() if "Join" in x and "parent" in x]
    assert joins and all("f#" in x for x in joins)


def test_vertex_pairs_are_made_without_shuffling_pairs(spark, monkeypatch):
    """all pairs of an edge's vertices were shuffled to make them distinct."""
    monkeypatch.setattr(adjacency, "SOME", 20)
    monkeypatch.setattr(adjacency, "SENT", 16)
    data = {e: sorted({(e * 7 + i * i) % 40 for i in range(2 + e % 9)}) for e in range(30)}
    h = graph(spark, data, dict.fromkeys(range(40), ""))
    want = sorted({p for vs in data.values() for p in itertools.combinations(vs, 2)})
    assert rows(h.vertex_adjacency()) == want
    named = spark.createDataFrame([(e, f"é{v}", "") for e, vs in data.items() for v in vs], "e long, v string, label string")
    assert rows(HypergraphFrame.from_incidence(named).vertex_adjacency()) == sorted({tuple(sorted((f"é{a}", f"é{b}"), key=str.encode)) for a, b in want})
    assert "Aggregate" not in h.vertex_adjacency()._jdf.queryExecution().optimizedPlan().toString()
    assert h.subhypergraph(h.edges.where("e < 0").select("e")).vertex_adjacency().count() == 0


def test_statistics_hold_one_hypergraph_at_a_time(spark, data, monkeypatch):
    """all hypergraphs were parts of one query, and their files stayed."""
    from pathlib import Path

    made = []
    plain = workloads.forget
    monkeypatch.setattr(workloads, "forget", lambda df: (made.append(Path(df._written_path)), plain(df)))
    got = workloads.dataset_statistics(spark, data, ("nation_members", "coactive_10m"))
    assert "Scan parquet" not in got._jdf.queryExecution().executedPlan().toString() and len(made) == 2 and not any(p.exists() for p in made)
    assert [r["hypergraph"] for r in got.collect()] == ["nation_members", "coactive_10m"]


def test_effort_in_tables_equals_the_search(spark, monkeypatch):
    """the space was gathered on the driver, and the search ended at 2,000 embeddings."""
    data = {e: sorted({(e * 7 + i * i * (e % 3 + 1)) % 25 for i in range(2 + e % 3)}) for e in range(60)}
    h = graph(spark, data, {v: "AB"[v % 5 == 0] for v in range(25)})
    found = 0
    for pair in ([1, 2, 3], [3, 4]), ([1, 2], [2, 3]), ([1, 2, 5], [1, 2, 3]):
        p = PatternGraph.of(pair, {v: "AB"[v % 5 == 0] for v in range(25)})
        raw = build_space(p, h)
        for space in (raw, prune_to_fixpoint(p, raw)):
            want = measures.effort(p, space)
            found += want["embeddings"]
            got = measures.effort_of_pairs(p, space)
            assert {x: got[x] for x in ("checks", "extended", "dead_ends", "embeddings")} == {x: want[x] for x in ("checks", "extended", "dead_ends", "embeddings")}
    assert found > 0
    monkeypatch.setattr(workloads, "effort", None)  # no gathering
    monkeypatch.setattr(workloads, "hypergraph", lambda *_: h)
    assert not any(r["truncated"] for r in workloads.unlabelled_difficulty(spark, "", 2, 1, most=None).collect())
