"""What the operators share: reading tables, written intermediate tables, size-checked broadcasts, ranks without one-task windows."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A side of a join is broadcast only if its written table is at most this large.
BROADCAST_BYTES = 16 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share (spark.checkpoint.dir); a folder of our own only where the setting is absent and all runs in one process, as in local tests."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = getattr(spark, "_own_shared_folder", None) or tempfile.mkdtemp(prefix="hyperpattern-")
        spark._own_shared_folder = found
    return found.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage, survives lost executors, and gives the planner true sizes."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def _file_system(spark: SparkSession, path: str):
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    return jpath.getFileSystem(spark._jsc.hadoopConfiguration()), jpath


def written_bytes(df: DataFrame) -> int:
    fs, path = _file_system(df.sparkSession, df._written_path)
    return fs.getContentSummary(path).getLength()


def forget(*frames: DataFrame) -> None:
    """Removes tables made by written() that nothing reads any more."""
    for df in frames:
        fs, path = _file_system(df.sparkSession, df._written_path)
        fs.delete(path, True)


def let_go(spark: SparkSession) -> None:
    """The driver's two processes give back what ended jobs left there: Python its cycles, Arrow what was freed, the JVM broadcasts that nothing reads and the heap it grew by."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    spark._jvm.System.gc()


def small(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """A written table with a broadcast hint if its files are at most `limit` bytes, else the table as it is for a shuffled join."""
    return F.broadcast(df) if written_bytes(df) <= limit else df


def text_or_empty(c: str | Column = "text") -> Column:
    return F.coalesce(F.col(c) if isinstance(c, str) else c, F.lit(""))


def ranked(df: DataFrame, key: str, order: list[str], name: str, per_bucket: int = 200_000, rows: int | None = None) -> DataFrame:
    """df with column `name`: a gapless number from 0 within each value of `key`.

    A value may hold any share of the rows, so rows are numbered inside hash buckets of a value and shifted by the
    sizes of the buckets before; the table of sizes has one row per value and bucket.
    """
    rows = df.count() if rows is None else rows
    buckets = max(1, -(-rows // per_bucket), int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = df.withColumn("_b", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    sizes = dealt.groupBy(key, "_b").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(key).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(key, "_b", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    own = F.row_number().over(Window.partitionBy(key, "_b").orderBy(*order)) - 1
    return dealt.withColumn("_own", own).join(starts, [key, "_b"]).withColumn(name, (F.col("_start") + F.col("_own")).cast("long")).drop("_b", "_own", "_start")
