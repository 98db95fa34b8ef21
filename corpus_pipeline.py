"""A training corpus in five stages; each works on all that the stage before kept, and its decisions take effect.

toxicity        documents that the nearest labelled examples vote toxic go
line dedup      of lines that are alike, all but the first go; a document may end up empty, and stays
near dedup      one document of each class of near duplicates stays
decontamination documents that contain benchmark passages go
packing         what is left becomes sequences of at most 1024 tokens
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hyperpattern.llm.decontam import drop_contaminated
from hyperpattern.llm.line_dedup import without_repeated_lines
from hyperpattern.llm.near_dup import keep_one_each
from hyperpattern.llm.packing import pack_documents
from hyperpattern.llm.shared import let_go, table, written
from hyperpattern.llm.toxicity import drop_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_toxic(docs, table(spark, sf_dir, "labels"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_repeated_lines(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs)


STAGES = [
    ("toxicity", toxicity),
    ("line_dedup", line_dedup),
    ("near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("packing", packing),
]

#: No stage before the last can be expressed in SQL as it is (a fitted model, signatures, components).
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
        let_go(spark)  # a stage's model and broadcasts would stand beside those of the next
    return STAGES[-1][1](spark, docs, sf_dir)
