"""Cost measures of the experiments, and their summaries."""

from __future__ import annotations

import contextlib
import json
import threading
import time
import uuid
from collections.abc import Callable
from pathlib import Path

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .candidates import CandidateSpace, build_space, prune_to_fixpoint
from .cells import cell_check, extended_cells
from .localsearch import Searcher, gathered
from .model import HypergraphFrame
from .pattern import PatternGraph

SCHEMA = "hypergraph string, system string, size int, query_id string, seconds double, solved boolean, embeddings long, peak_bytes long"


def timed(spark: SparkSession, action: Callable[[], int], time_limit: float) -> tuple[float, bool, int | None, str]:
    """(seconds, solved, result, job group). The jobs of a run past the limit are cancelled, and it counts as unsolved."""
    sc, group = spark.sparkContext, uuid.uuid4().hex
    sc.setJobGroup(group, "timed run", interruptOnCancel=True)
    late = threading.Event()
    over = threading.Event()

    def stop() -> None:
        late.set()
        while not over.wait(0.2):  # a run between two jobs starts the next one
            sc.cancelJobGroup(group)

    timer = threading.Timer(time_limit, stop)
    timer.daemon = True
    timer.start()
    t, n = time.monotonic(), None
    try:
        n = action()
    except Exception:
        if not late.is_set():
            raise
    finally:
        s = time.monotonic() - t
        over.set()
        timer.cancel()
        sc.setLocalProperty("spark.jobGroup.id", None)
    return s, not late.is_set(), n, group


def peak_bytes(spark: SparkSession, group: str) -> int:
    """The most execution memory that the tasks of one stage of a job group took together, from Spark's status store."""
    tracker, store, most = spark.sparkContext.statusTracker(), spark.sparkContext._jsc.sc().statusStore(), 0
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            with contextlib.suppress(Py4JJavaError):  # a skipped stage has no attempt
                most = max(most, store.lastStageAttempt(stage).peakExecutionMemory())
    return most


def space_stats(p: PatternGraph, h: HypergraphFrame) -> dict:
    """Candidates and connections before and after the initial filter, rounds, removed shares, connections for each candidate."""
    before = build_space(p, h)
    after = prune_to_fixpoint(p, before)
    a, b = before.candidates.count(), after.candidates.count()
    c, d = before.connections.count() // 2, after.connections.count() // 2
    return {"cands_init": a, "cands_filtered": b, "conns_init": c, "conns_filtered": d, "rounds": after.rounds, "cands_removed_pct": 100 * (1 - b / a) if a else 0.0, "conns_removed_pct": 100 * (1 - d / c) if c else 0.0, "conns_per_cand": d / b if b else 0.0}


def effort(p: PatternGraph, space: CandidateSpace, order: str = "dynamic", prune: str = "both", most: int = 100_000) -> dict:
    """Engine-independent cost of a search over a small space: cell checks, partial embeddings, dead ends, embeddings (up to `most`), and seconds in checks."""
    live, members, links = gathered(space)
    s = Searcher(p, members, links, order, prune, False)
    spent = 0.0
    plain = s.fits

    def fits(*a):
        nonlocal spent
        t = time.perf_counter()
        out = plain(*a)
        spent += time.perf_counter() - t
        return out

    s.fits = fits
    n, began = 0, time.perf_counter()
    if len(live) == p.size:
        for n, _ in enumerate(s.search(live, {}), 1):  # noqa: B007
            if n == most:
                break
    total = time.perf_counter() - began
    return {"checks": s.checks, "extended": s.extended, "dead_ends": s.dead, "embeddings": n, "seconds": total, "verification_share": spent / total if total else 0.0}


def effort_of_pairs(p: PatternGraph, space: CandidateSpace) -> dict:
    """effort() of a pattern of two edges, dynamic order and both prunings, over a space of any size and for all embeddings: tables throughout.

    A seed's connections are what the search checks, those that pass are embeddings, and a seed without any is a dead end.
    seconds: of the job with the checks; verification_share: what it takes beyond the same job without them.
    """
    c, k = space.candidates, space.connections
    sizes = {r["q"]: r["n"] for r in c.groupBy("q").agg(F.count("*").alias("n")).collect()}
    if len(sizes) < 2:
        return {"checks": 0, "extended": 0, "dead_ends": 0, "embeddings": 0, "seconds": 0.0, "verification_share": 0.0}
    first = Searcher(p, {}, {}, "dynamic", "both", False).choose({q: range(n) for q, n in sizes.items()}, 0)
    vertex = c.schema["members"].dataType.elementType["v"].dataType.simpleString()
    side = lambda q, f, m: c.where(F.col("q") == q).select(F.col("f").alias(f), F.col("members").alias(m))
    pairs = k.where((F.col("q") == first) & (F.col("q2") == 1 - first)).select("f", "f2")
    pairs = pairs.join(side(first, "f", "m"), "f").join(side(1 - first, "f2", "m2"), "f2")
    cells = extended_cells(F.col("m"), F.create_map().cast(f"map<{vertex},bigint>"), F.lit(first))
    found = {}
    for kind, test in (("plain", F.size("m") + F.size("m2") > 0), ("checked", cell_check(p, F.col("m2"), cells, F.lit(1 - first), F.lit(1 << first).cast("long")))):
        began = time.perf_counter()
        by_seed = pairs.groupBy("f").agg(F.count("*").alias("n"), F.count_if(test).alias("kept"))
        found[kind] = by_seed.agg(F.sum("n").alias("n"), F.sum("kept").alias("kept"), F.count_if(F.col("kept") > 0).alias("live")).first(), time.perf_counter() - began
    (r, total), plain = found["checked"], found["plain"][1]
    kept = r["kept"] or 0
    return {"checks": r["n"] or 0, "extended": sizes[first] + kept, "dead_ends": sizes[first] - r["live"], "embeddings": kept, "seconds": total, "verification_share": max(0.0, 1 - plain / total)}


def with_cap(runs: DataFrame, cap: float = 600.0) -> DataFrame:
    """Runs of queries that some system solved; unsolved ones count as the cap."""
    some = runs.where("solved").select("hypergraph", "size", "query_id").distinct()
    return runs.join(some, ["hypergraph", "size", "query_id"], "left_semi").withColumn("seconds", F.when(F.col("solved"), F.col("seconds")).otherwise(F.lit(cap)))


def geometric_mean(c: str):
    return F.exp(F.avg(F.log(F.col(c))))


def summary(runs: DataFrame, cap: float = 600.0) -> DataFrame:
    """Geometric mean time and solved count by hypergraph, size and system, with totals (rollup)."""
    return with_cap(runs, cap).rollup("hypergraph", "size", "system").agg(geometric_mean("seconds").alias("gm_seconds"), F.count_if("solved").alias("solved"), F.count("*").alias("queries"), geometric_mean("embeddings").alias("gm_embeddings"), F.avg("peak_bytes").alias("avg_peak_bytes"))


def solved_ratio(runs: DataFrame) -> DataFrame:
    """Solved by a system over solved by any."""
    some = runs.where("solved").select("hypergraph", "size", "query_id").distinct().groupBy("hypergraph", "size").agg(F.count("*").alias("any"))
    own = runs.groupBy("hypergraph", "size", "system").agg(F.count_if("solved").alias("solved"))
    return own.join(some, ["hypergraph", "size"], "left").withColumn("ratio", F.col("solved") / F.col("any"))


def speedups(runs: DataFrame, base: str, cap: float = 600.0) -> DataFrame:
    """Geometric mean of each system over that of `base`."""
    gm = with_cap(runs, cap).groupBy("hypergraph", "size", "system").agg(geometric_mean("seconds").alias("gm"))
    own = gm.where(F.col("system") == base).select("hypergraph", "size", F.col("gm").alias("base_gm"))
    return gm.where(F.col("system") != base).join(own, ["hypergraph", "size"]).select("hypergraph", "size", "system", (F.col("gm") / F.col("base_gm")).alias("speedup"))


def same_rows(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def event_log_peaks(path: str) -> dict[str, int]:
    """From a Spark event log: peak execution memory of a task, bytes spilled, shuffle bytes written."""
    out = {"peak_task_bytes": 0, "spilled_bytes": 0, "shuffle_bytes": 0}
    for line in Path(path).open(errors="replace"):
        if '"SparkListenerTaskEnd"' in line:
            m = json.loads(line).get("Task Metrics") or {}
            out["peak_task_bytes"] = max(out["peak_task_bytes"], m.get("Peak Execution Memory", 0))
            out["spilled_bytes"] += m.get("Disk Bytes Spilled", 0)
            out["shuffle_bytes"] += m.get("Shuffle Write Metrics", {}).get("Shuffle Bytes Written", 0)
    return out
