"""Catalogue queries against their SQL on the smallest tables; streams, sources, walks and sinks."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from hyperpattern import search, sources, walks
from hyperpattern.candidates import build_space, init_candidates, prune_to_fixpoint
from hyperpattern.carriers import NAMES, hypergraph
from hyperpattern.measures import timed
from hyperpattern.model import HypergraphFrame, signature_hash
from hyperpattern.pattern import PatternGraph
from hyperpattern.search import match
from hyperpattern.streaming.standing import standing_query, windows
from hyperpattern.workloads import unlabelled_difficulty

SOME = ["stats_basket_type", "stats_vec_buckets", "match_coactive_pair", "filtered_coactive_chain", "walks_coactive", "disconnected_coactive", "baseline_overlap_coactive_triangle", "prune_none_coactive_chain", "relational_as_of_join", "relational_interval_join", "relational_top_vertices", "wavefront_supply_regions", "wavefront_batches_coactive_chain", "match_walk_basket_brand", "match_walk_turn_words", "non_simple_page_links", "bipartite_without_arity", "relational_json", "relational_cube"]


def plain(v):
    return round(v, 6) if isinstance(v, float) else int(v) if isinstance(v, bool) else v


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, data, name):
    con = duckdb.connect()
    for t in os.listdir(data):
        con.sql(f"create view {t.removesuffix('.parquet')} as select * from '{data}/{t}'")
    df = entry.queries()[name](spark, data)
    sql = con.sql(entry.oracle_sql()[name])
    assert sorted(df.columns) == sorted(sql.columns)
    got = sorted((tuple(plain(r[c]) for c in sorted(df.columns)) for r in df.collect()), key=str)
    at = [sql.columns.index(c) for c in sorted(sql.columns)]
    assert got == sorted((tuple(plain(r[i]) for i in at) for r in sql.fetchall()), key=str)


def test_entry_and_keys(spark, data):
    found = entry.entry(spark)
    assert found.columns == ["embedding_id", "q", "f"] and found.count() >= 3
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_walks_find_themselves(spark, data):
    h = hypergraph(spark, data, "basket_type").materialise()
    w = walks.sample(h, 3, 2)
    for p in walks.patterns(h, w).values():
        assert p.size == 3 and len(p.components()) == 1
        assert not match(h, p).isEmpty()
    assert walks.sample(h, 3, 4, max_vertices=1).isEmpty()


def test_index_round_trip(spark, data, tmp_path):
    h = hypergraph(spark, data, "basket_type")
    h.write_index(str(tmp_path / "index"), 2)
    assert HypergraphFrame.read_index(spark, str(tmp_path / "index")).edges.count() == h.edges.count()


def test_the_index_is_asked_by_literal_signatures(spark, data, tmp_path):
    h = hypergraph(spark, data, "basket_type")
    h.write_index(str(tmp_path / "index"), 2)
    assert all(signature_hash(r["sig"]) == r["sig_id"] for r in h.edges.select("sig", "sig_id").limit(300).collect())
    p = PatternGraph.of([[1, 2], [2, 3]], {1: "STANDARD", 2: "ECONOMY", 3: "PROMO"})
    found = init_candidates(p, HypergraphFrame.read_index(spark, str(tmp_path / "index")))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "sig_id" in plan[plan.index("PushedFilters") :].split("]")[0]


def test_wavefront_stops_when_the_limit_is_met(spark, data, monkeypatch):
    h = hypergraph(spark, data, "supply_region").materialise()
    p = PatternGraph.of([[1, 2], [2, 3]], {1: "ASIA", 2: "EUROPE", 3: "AFRICA"})
    runs, plain_run = [], search.wavefront
    monkeypatch.setattr(search, "wavefront", lambda *a: runs.append(1) or plain_run(*a))
    space = prune_to_fixpoint(p, build_space(p, h))
    everything = search.wavefront_in_batches(p, space, batch=1)
    n = len(runs)
    assert n > 1 and everything.count() == plain_run(p, space).count() > 1
    runs.clear()
    assert search.wavefront_in_batches(p, space, batch=1, limit=1).limit(1).count() == 1 and len(runs) < n


def test_a_run_past_its_limit_is_stopped(spark):
    def slow():
        return spark.range(0, 10**13, 1, 4).selectExpr("sum(sqrt(id))").collect()

    seconds, solved, found, group = timed(spark, slow, 2.0)
    assert not solved and found is None and seconds < 30
    assert timed(spark, lambda: spark.range(9).groupBy().count().first()[0], 60.0)[1:3] == (True, 9)


def test_sources_and_sink(spark, tmp_path):
    (tmp_path / "a.csv").write_text("e,v,label\n1,1,A\n1,2,B\n2,2,B\n2,3,A\n")
    (tmp_path / "a.json").write_text('{"e":1,"v":1,"label":"A"}\n{"e":1,"v":2,"label":"B"}\n')
    (tmp_path / "a.txt").write_text("1,2\n2, 3\n\n")
    assert sources.from_csv(spark, str(tmp_path / "a.csv")).edges.count() == 2
    assert sources.from_json(spark, str(tmp_path / "a.json")).edges.count() == 1
    assert sources.from_edge_lists(spark, str(tmp_path / "a.txt")).edges.count() == 2
    labels = spark.createDataFrame([(1, "A"), (2, "B")], "v long, label string")
    assert sources.from_edge_lists(spark, str(tmp_path / "a.txt"), labels).stats().first()["n_labels"] == 3
    found = spark.createDataFrame([(1, 2)], "m0 long, m1 long")
    for q in ("x", "y", "x"):
        sources.write_embeddings(found, q, str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 2


def test_streamed_equals_batch_and_late_events_change_nothing(spark, tmp_path):
    rows = [(f"2024-01-01 00:{m:02d}:{s:02d}", u, "A") for m, s, u in ((0, 5, 1), (1, 0, 2), (11, 0, 2), (12, 0, 3), (21, 0, 3), (22, 0, 4), (45, 0, 9))]
    schema = "ts string, user_id long, label string"
    src, store = tmp_path / "events", str(tmp_path / "store")
    src.mkdir()
    for i, part in enumerate((rows[:3], rows[3:5], rows[5:], [("2024-01-01 00:00:30", 7, "A")], [("2024-01-01 01:30:00", 9, "A")])):
        spark.createDataFrame(part, schema).withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(str(src / f"p{i}"))
    p = PatternGraph.of([[1, 2], [2, 3]], {1: "A", 2: "A", 3: "A"})
    stream = spark.readStream.schema("ts timestamp, user_id long, label string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(src))
    seen = []
    q = standing_query(windows(stream), p, store, lambda df, n: seen.extend(tuple(r) for r in df.collect()), str(tmp_path / "checkpoint"))
    q.processAllAvailable()
    q.stop()
    kept = HypergraphFrame(spark.read.parquet(store).drop("batch"))
    batch = sorted(tuple(r) for r in match(kept, p).collect())
    assert sorted(seen) == batch and len(batch) > 0
    assert all(m["v"] != 7 for r in kept.edges.collect() for m in r["members"])


def test_stateful_streams(spark, tmp_path):
    from hyperpattern.streaming.standing import new_edges, recent_by_signature

    src = tmp_path / "edges"
    src.mkdir()
    for i, part in enumerate(([("A", 1000, [1, 2]), ("A", 1500, [1, 2])], [("A", 6000, [1, 3]), ("B", 6000, [4])])):
        spark.createDataFrame(part, "sig string, at long, members array<long>").coalesce(1).write.mode("append").parquet(str(src / f"p{i}"))
    stream = spark.readStream.schema("sig string, at long, members array<long>").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(src))
    seen, kept = [], []
    for frame, out, mode in ((recent_by_signature(stream, 3000), seen, "update"), (new_edges(stream.withColumn("ts", F.timestamp_millis("at")), "ts"), kept, "append")):
        q = frame.writeStream.outputMode(mode).option("checkpointLocation", str(tmp_path / f"c-{mode}")).foreachBatch(lambda df, n, out=out: out.extend(df.collect())).trigger(availableNow=True).start()
        assert q.awaitTermination(90)
    assert {(r["sig"], r["n"]) for r in seen if r["latest"] == 6000} == {("A", 1), ("B", 1)}
    assert sorted(r["members"] for r in kept) == [[1, 2], [1, 3], [4]]


@pytest.mark.parametrize("name", ["experiment_dataset_statistics_all"])
def test_whole_query_equals_sql(spark, data, name):
    test_query_equals_sql(spark, data, name)


def test_whole_queries_leave_nothing_out(spark, data, tmp_path):
    spark.sql("select 1L as event_id, 2L as user_id, 'view' as event_type, timestamp '2024-01-10 00:00:00' as ts, 1.0D as value").write.parquet(f"{tmp_path}/events.parquet")
    assert [tuple(r) for r in entry.queries()["relational_interval_join"](spark, str(tmp_path)).collect()] == [(1, 1)]
    assert {r["hypergraph"] for r in entry.queries()["experiment_dataset_statistics_all"](spark, data).collect()} == set(NAMES)
    rows = unlabelled_difficulty(spark, data, 2, 1, most=2).collect()
    assert any(r["truncated"] for r in rows) and all(r["truncated"] == (r["embeddings"] == 2) for r in rows)
