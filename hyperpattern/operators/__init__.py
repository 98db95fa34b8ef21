"""Relational operators that users of hypergraphs need beyond Spark's own: range and as-of joins, top-k by group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def interval_join(points: DataFrame, at: str, spans: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Pairs with lo <= at < hi by an equi-join on buckets of `width`; choose it near the usual length of a span."""
    p = points.withColumn("_bucket", F.floor(F.col(at) / width))
    s = spans.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    return p.join(s, "_bucket").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_bucket")


def interval_counts(points: DataFrame, at: str, spans: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """points with n_spans, in how many of the spans lo <= at < hi each falls; those in none are left out.

    Without pairs: spans that have begun less those that have ended, summed along the line. Times meet in buckets of
    `width`, to which what all earlier ones leave over is added, so a bucket holds each of its times once.
    """
    whole = spans.where(F.col(lo) < F.col(hi))
    ends = whole.select(F.col(lo).alias(at), F.lit(1).alias("_d")).unionByName(whole.select(F.col(hi).alias(at), F.lit(-1).alias("_d")))
    steps = ends.unionByName(points.where(F.col(at).isNotNull()).select(at, F.lit(0).alias("_d"))).groupBy(at).agg(F.sum("_d").alias("_d")).withColumn("_bucket", F.floor(F.col(at) / width))
    total = steps.groupBy("_bucket").agg(F.sum("_d").alias("_all"))
    carried = total.select("_bucket", (F.sum("_all").over(Window.orderBy("_bucket")) - F.col("_all")).alias("_before"))
    inside = F.sum("_d").over(Window.partitionBy("_bucket").orderBy(at))
    level = steps.withColumn("_in", inside).join(carried, "_bucket").select(at, (F.col("_in") + F.col("_before")).alias("n_spans")).where("n_spans > 0")
    return points.join(level, at).select(*points.columns, "n_spans")


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with `value` of the latest row of right of the same key that isn't later. One sort by key and time, no pairs."""
    a = left.select(F.struct(*left.columns).alias("_row"), F.col(key).alias("_k"), F.col(at).alias("_t"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(key).alias("_k"), F.col(at).alias("_t"), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy("_k").orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_v", F.last("_v", ignorenulls=True).over(w))
    return both.where("_side = 1").select("_row.*", F.col("_v").alias(value))


def top_by_group(df: DataFrame, group: list[str], order: list[Column], k: int) -> DataFrame:
    w = Window.partitionBy(*group).orderBy(*order)
    return df.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_r")
