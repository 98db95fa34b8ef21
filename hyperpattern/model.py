"""Hypergraphs as DataFrames: incidence (e, v, label) and edges (e, arity, sig_id, sig, members, elabel)."""

from __future__ import annotations

from dataclasses import dataclass

import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .adjacency import vertex_pairs
from .storage import held


def signature(labels: Column) -> Column:
    """Canonical form of a multiset of labels: its sorted array."""
    return F.sort_array(labels)


def signature_hash(labels) -> int:
    """sig_id of a sorted list of labels: what xxhash64 gives for the array, each label hashed with the hash so far as its seed."""
    seed = 42
    for x in labels:
        seed = xxhash.xxh64_intdigest(x.encode(), seed)
    return seed - (1 << 64) if seed >> 63 else seed


def signature_agg(rows: DataFrame, keys: list[str], label: str = "label") -> DataFrame:
    """keys, sig: the signature of each group's labels."""
    return rows.groupBy(*keys).agg(signature(F.collect_list(label)).alias("sig"))


def member_labels(members: Column) -> Column:
    return signature(F.transform(members, lambda x: x["l"]))


@dataclass
class HypergraphFrame:
    """edges: e, arity, sig_id (hash of sig), sig (sorted labels), members (sorted array of v, l), elabel (null: none)."""

    edges: DataFrame

    @classmethod
    def from_incidence(cls, rows: DataFrame, e: str = "e", v: str = "v", label: str = "label", elabel: str | None = None) -> HypergraphFrame:
        """Rows with a null edge or vertex are left out; a null label is the empty label; of several labels of a vertex the least counts."""
        rows = rows.where(F.col(e).isNotNull() & F.col(v).isNotNull())
        name = F.col(elabel).cast("string") if elabel else F.lit(None).cast("string")
        flat = rows.groupBy(F.col(e).alias("e"), F.col(v).alias("v")).agg(F.min(F.coalesce(F.col(label).cast("string"), F.lit(""))).alias("l"), F.min(name).alias("elabel"))
        grouped = flat.groupBy("e").agg(F.sort_array(F.collect_list(F.struct("v", "l"))).alias("members"), F.min("elabel").alias("elabel"))
        return cls(cls._described(grouped))

    @staticmethod
    def _described(grouped: DataFrame) -> DataFrame:
        sig = member_labels(F.col("members"))
        out = grouped.withColumn("sig", sig).withColumn("arity", F.size("members"))
        return out.select("e", "arity", F.xxhash64("sig").alias("sig_id"), "sig", "members", "elabel")

    def simplify(self, drop_repeated: bool = True, drop_unit_edges: bool = True) -> HypergraphFrame:
        """Of edges with equal vertex sets (and edge labels) the smallest id stays; edges of one vertex go."""
        edges = self.edges.where("arity > 1") if drop_unit_edges else self.edges
        if drop_repeated:
            keep = edges.groupBy("members", "elabel").agg(F.min("e").alias("e"))
            edges = HypergraphFrame._described(keep)
        return HypergraphFrame(edges)

    def materialise(self) -> HypergraphFrame:
        return HypergraphFrame(held(self.edges, "hypergraph"))

    def incidence(self) -> DataFrame:
        return self.edges.select("e", F.inline("members")).withColumnRenamed("l", "label")

    def vertices(self) -> DataFrame:
        return self.incidence().select("v", "label").distinct()

    def stats(self) -> DataFrame:
        """n_vertices, n_edges, n_labels, max_arity, avg_arity, n_signatures."""
        by_edge = self.edges.agg(F.count("*").alias("n_edges"), F.max("arity").cast("long").alias("max_arity"), F.round(F.avg("arity"), 6).alias("avg_arity"), F.countDistinct("sig").alias("n_signatures"))
        by_vertex = self.vertices().agg(F.countDistinct("v").alias("n_vertices"), F.countDistinct("label").alias("n_labels"))
        return by_vertex.crossJoin(by_edge).select("n_vertices", "n_edges", "n_labels", "max_arity", "avg_arity", "n_signatures")

    def signature_partitions(self) -> DataFrame:
        """sig (joined by '|'), n_edges."""
        return self.edges.groupBy(F.array_join("sig", "|").alias("sig")).agg(F.count("*").alias("n_edges"))

    def edge_adjacency(self) -> DataFrame:
        """a < b, n_shared: pairs of edges that share vertices. Quadratic in a vertex's degree, as its result is."""
        i = self.incidence()
        pairs = i.select(F.col("e").alias("a"), "v").join(i.select(F.col("e").alias("b"), "v"), "v").where("a < b")
        return pairs.groupBy("a", "b").agg(F.count("*").alias("n_shared"))

    def vertex_adjacency(self) -> DataFrame:
        """a < b: vertices that share an edge."""
        return vertex_pairs(self.edges)

    def subhypergraph(self, edge_ids: DataFrame) -> HypergraphFrame:
        return HypergraphFrame(self.edges.join(edge_ids.select("e"), "e", "left_semi"))

    def create_views(self, prefix: str) -> None:
        self.edges.createOrReplaceTempView(f"{prefix}_edges")
        self.incidence().createOrReplaceTempView(f"{prefix}_incidence")
        self.vertices().createOrReplaceTempView(f"{prefix}_vertices")

    def write_index(self, path: str, parts: int | None = None) -> None:
        """The signature index: edges dealt and sorted by signature hash, with row-group statistics and a bloom filter on it."""
        dealt = self.edges.repartition(parts, "sig_id") if parts else self.edges.repartition("sig_id")
        dealt.sortWithinPartitions("sig_id").write.option("parquet.bloom.filter.enabled#sig_id", "true").mode("overwrite").parquet(path)

    @classmethod
    def read_index(cls, spark, path: str) -> HypergraphFrame:
        return cls(spark.read.parquet(path))
