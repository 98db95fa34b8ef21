"""The running example: every stage, every variant, every baseline."""

import pytest
from pyspark.sql import functions as F

from hyperpattern.baselines import BASELINES
from hyperpattern.candidates import adjacent_candidates, build_space, prune_to_fixpoint, prune_worklist
from hyperpattern.cells import valid_by_cells, valid_by_subsets
from hyperpattern.functions import parse, register
from hyperpattern.measures import effort, space_stats
from hyperpattern.model import HypergraphFrame
from hyperpattern.order import ORDERS
from hyperpattern.pattern import PatternGraph
from hyperpattern.search import PRUNES, count_embeddings, estimate_count, exists_embedding, is_isomorphic, match, wavefront, witness

DATA = {1: [1, 2, 3, 4, 5], 2: [2, 8, 9, 11, 12], 3: [1, 2, 10], 4: [1, 2, 11], 5: [2, 3, 10], 6: [6, 7, 13], 7: [1, 12], 8: [3, 10], 9: [12, 13]}
QUERY = PatternGraph.of([[1, 2, 3, 4, 5], [1, 2, 6], [1, 7], [2, 3, 6]], {u: "B" if u in (4, 5) else "A" for u in range(1, 8)})
ONLY = [(1, 3, 7, 5)]


@pytest.fixture(scope="module")
def h(spark):
    rows = [(e, v, "B" if v in (4, 5, 8, 9) else "A") for e, vs in DATA.items() for v in vs]
    return HypergraphFrame.from_incidence(spark.createDataFrame(rows, "e long, v long, label string")).materialise()


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_space_and_filter(h):
    space = build_space(QUERY, h)
    assert space.candidates.count() == 13 and space.connections.count() == 40
    kept = prune_to_fixpoint(QUERY, space)
    assert rows(kept.candidates.select("q", "f")) == [(0, 1), (0, 2), (1, 3), (1, 4), (2, 7), (2, 8), (3, 3), (3, 4), (3, 5)]
    assert kept.connections.count() == 32 and kept.rounds == 3
    again = prune_worklist(QUERY, space)
    assert rows(again.candidates.select("q", "f")) == rows(kept.candidates.select("q", "f"))
    assert rows(adjacent_candidates(kept.connections, 1, 3, 3)) == [(4,), (5,)]
    one = prune_to_fixpoint(QUERY, space, 1)
    assert one.candidates.count() == 10


@pytest.mark.parametrize("prune", PRUNES)
def test_pruning_variants(h, prune):
    kept = prune_to_fixpoint(QUERY, build_space(QUERY, h))
    assert rows(wavefront(QUERY, kept, prune=prune)) == ONLY
    assert rows(match(h, QUERY, prune=prune, engine="local")) == ONLY


@pytest.mark.parametrize("order", ORDERS)
def test_orders(h, order):
    assert rows(match(h, QUERY, order=order, engine="local")) == ONLY


@pytest.mark.parametrize("name", BASELINES)
def test_baselines(h, name):
    assert rows(BASELINES[name](h, QUERY)) == ONLY


def test_exact_tests_of_a_mapping(spark, h):
    m = spark.createDataFrame([(1, 3, 7, 5), (1, 3, 8, 4)], "m0 long, m1 long, m2 long, m3 long")
    assert rows(valid_by_cells(QUERY, m, h.edges)) == ONLY == rows(valid_by_subsets(QUERY, m, h.edges))


def test_bitmaps():
    assert [QUERY.bitmaps[u] for u in (1, 2, 3)] == [0b0111, 0b1011, 0b1001]
    assert QUERY.cells(3, 0b0011).count((0b1011, "A")) == 1


def test_witness_counts_and_existence(h):
    found = match(h, QUERY)
    w = witness(h, QUERY, found).collect()
    assert {r["u"]: r["v"] for r in w if r["u"] in "12367"} == {"1": 1, "2": 2, "3": 3, "6": 10, "7": 12}
    assert count_embeddings(h, QUERY) == 1 and exists_embedding(h, QUERY)
    assert not exists_embedding(h, PatternGraph.of([[1, 2]], {1: "C", 2: "A"}))
    assert estimate_count(h, QUERY, one_in=1) == 1
    assert is_isomorphic(h, h)


def test_single_edge_and_bipartite_without_arity(h):
    one = PatternGraph.of([[1, 2]], {1: "A", 2: "A"})
    assert rows(match(h, one)) == [(7,), (8,), (9,)]
    assert BASELINES["bipartite"](h, one, "none").count() > 3
    assert rows(BASELINES["bipartite"](h, one, "signature")) == [(7,), (8,), (9,)]


def test_disconnected(h):
    p = PatternGraph.of([[1, 2], [3, 4]], {i: "A" for i in range(1, 5)})
    assert rows(match(h, p)) == [(7, 8), (8, 7), (8, 9), (9, 8)]


def test_measures(h):
    s = space_stats(QUERY, h)
    assert (s["cands_init"], s["cands_filtered"], s["conns_init"], s["conns_filtered"]) == (13, 9, 20, 16)
    kept = prune_to_fixpoint(QUERY, build_space(QUERY, h))
    pruned, plain = effort(QUERY, kept), effort(QUERY, kept, prune="none")
    assert pruned["embeddings"] == plain["embeddings"] == 1 and pruned["extended"] <= plain["extended"]


def test_statistics_and_structure(spark, h):
    r = h.stats().first()
    assert (r["n_vertices"], r["n_edges"], r["n_labels"], r["max_arity"]) == (13, 9, 2, 5)
    assert h.edge_adjacency().where("a = 1 and b = 3").first()["n_shared"] == 2
    assert h.vertex_adjacency().where("a = 4 and b = 5").count() == 1
    assert h.subhypergraph(spark.createDataFrame([(1,), (9,)], "e long")).stats().first()["n_edges"] == 2


def test_cleanup_and_nulls(spark):
    rows_ = [(1, 1, "A"), (1, 2, None), (2, 2, None), (2, 1, "A"), (3, 5, "A"), (None, 1, "A"), (4, None, "A")]
    h = HypergraphFrame.from_incidence(spark.createDataFrame(rows_, "e long, v long, label string"))
    assert sorted(r["e"] for r in h.edges.collect()) == [1, 2, 3]
    assert [r["e"] for r in h.simplify().edges.collect()] == [1]


def test_sql_functions(spark):
    register(spark)
    r = spark.sql("select signature(array('b','a')) s, same_multiset(array('a','b'), array('b','a')) m, cell_bitmap(array(0, 2)) c").first()
    assert (r["s"], r["m"], r["c"]) == (["a", "b"], True, 5)
    assert spark.sql("select * from pattern_edges('a:A b:B; b c:A')").count() == 4
    assert parse("a:A b:B; b c:A").overlaps == {(0, 1): ["B"]}


def test_no_set_is_intersected_in_the_cell_check(h):
    from hyperpattern.cells import cell_check

    df = h.edges.select(cell_check(QUERY, F.col("members"), F.create_map().cast("map<bigint,bigint>"), F.lit(0), F.lit(0).cast("long")).alias("x"))
    assert "array_intersect" not in df._jdf.queryExecution().toString()
