"""Event windows as hyperedges, and the embeddings that each micro-batch of new hyperedges completes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..model import HypergraphFrame
from ..pattern import PatternGraph
from ..search import match


def windows(events: DataFrame, length: str = "10 minutes", delay: str = "0 seconds", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """e (start of the window in seconds), members of a stream (or table) with ts, user_id, label.

    Tumbling windows, sliding ones with `slide`, sessions of a user with `gap`. Events later than the watermark never
    change a window that was given out.
    """
    at = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    if gap:
        span, keys = F.session_window("ts", gap), ["user_id"]
    else:
        span, keys = (F.window("ts", length, slide) if slide else F.window("ts", length)), []
    sets = at.groupBy(span.alias("w"), *keys).agg(F.sort_array(F.collect_set(F.struct(F.col("user_id").alias("v"), F.col("label").alias("l")))).alias("members"))
    return sets.select(F.col("w.start").cast("long").alias("e"), *keys, "members")


def delta_matches(old: DataFrame, new: DataFrame, p: PatternGraph) -> DataFrame:
    """Embeddings over old and new edges (tables of `edges` of a HypergraphFrame) that use a new edge."""
    found = match(HypergraphFrame(old.unionByName(new)), p)
    fresh = new.select(F.col("e").alias("_e"))
    uses = None
    for q in range(p.size):
        hit = found.join(fresh, F.col(f"m{q}") == F.col("_e"), "left_semi")
        uses = hit if uses is None else uses.unionByName(hit)
    return uses.distinct()


def standing_query(edge_stream: DataFrame, p: PatternGraph, store: str, report: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Runs delta_matches on every micro-batch of (e, members). Edges are kept in `store`, a Parquet folder by batch; a batch that is run again replaces its own."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        edges = HypergraphFrame._described(batch.select("e", "members").withColumn("elabel", F.lit(None).cast("string")))
        edges.withColumn("batch", F.lit(number)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(store)
        kept = spark.read.schema(edges.schema.add("batch", "long")).parquet(store)
        old, new = kept.where(F.col("batch") < number).drop("batch"), kept.where(F.col("batch") == number).drop("batch")
        if not new.isEmpty():
            report(delta_matches(old, new, p), number)

    return edge_stream.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(step).start()


def new_edges(edge_stream: DataFrame, ts: str, delay: str = "1 hour") -> DataFrame:
    """Hyperedges (with a time column ts and members) whose vertex set wasn't seen within the watermark."""
    return edge_stream.withColumn("members_key", F.to_json("members")).withWatermark(ts, delay).dropDuplicatesWithinWatermark(["members_key"]).drop("members_key")


def recent_by_signature(edge_stream: DataFrame, ttl_ms: int) -> DataFrame:
    """sig, n, latest: for each signature of (sig string, at long in ms), how many hyperedges came within ttl_ms of the latest, kept as state.

    The state of a signature is the times still inside, so it is bounded by the rate times ttl_ms; there is one for each
    signature ever seen.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, frames, state: GroupState):
        times = list(state.get[0]) if state.exists else []
        for f in frames:
            times += f["at"].tolist()
        latest = max(times)
        times = [t for t in times if t > latest - ttl_ms]
        state.update((times,))
        yield pd.DataFrame({"sig": [key[0]], "n": [len(times)], "latest": [latest]})

    return edge_stream.groupBy("sig").applyInPandasWithState(update, "sig string, n long, latest long", "times array<long>", "update", GroupStateTimeout.NoTimeout)
