"""Hypergraphs from files, and results to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import HypergraphFrame

INCIDENCE = "e long, v long, label string"


def from_csv(spark: SparkSession, path: str, header: bool = True) -> HypergraphFrame:
    return HypergraphFrame.from_incidence(spark.read.schema(INCIDENCE).option("header", header).csv(path))


def from_json(spark: SparkSession, path: str) -> HypergraphFrame:
    return HypergraphFrame.from_incidence(spark.read.schema(INCIDENCE).json(path))


def from_parquet(spark: SparkSession, path: str) -> HypergraphFrame:
    return HypergraphFrame.from_incidence(spark.read.parquet(path))


def from_edge_lists(spark: SparkSession, path: str, labels: DataFrame | None = None) -> HypergraphFrame:
    """A hyperedge a line, vertices parted by commas; its id is the hash of the line. labels: v, label (absent: unlabelled)."""
    lines = spark.read.text(path).where(F.length(F.trim("value")) > 0)
    rows = lines.select(F.xxhash64("value").alias("e"), F.explode(F.split("value", ",")).alias("_v")).select("e", F.trim("_v").cast("long").alias("v"))
    named = rows.join(labels, "v", "left") if labels is not None else rows.withColumn("label", F.lit(""))
    return HypergraphFrame.from_incidence(named)


def write_embeddings(found: DataFrame, query_id: str, path: str, fmt: str = "parquet") -> None:
    """Results of several queries in one folder, a partition for each; one query is overwritten alone."""
    found.withColumn("query_id", F.lit(query_id)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("query_id").format(fmt).save(path)
