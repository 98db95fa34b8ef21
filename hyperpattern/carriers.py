"""Hypergraphs on the given tables: one SQL text each for (e, v, label[, elabel]), valid in Spark and, with other spellings, in DuckDB."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from .model import HypergraphFrame

SPARK = {
    "minute": lambda c, n: f"CAST(floor(unix_timestamp(CAST({c} AS TIMESTAMP)) / {60 * n}) AS BIGINT)",
    "day": lambda c: f"date_format({c}, 'yyyy-MM-dd')",
    "words": lambda c: rf"explode(regexp_extract_all(lower({c}), '[a-z]+', 0))",
    "links": lambda c: rf"""explode(regexp_extract_all({c}, 'href="([^"]*)"', 1))""",
    "signs": lambda c, t: "concat(" + ", ".join([f"'{t}:'"] + [f"CASE WHEN {c}[{i}] >= 0 THEN '1' ELSE '0' END" for i in range(8 * t, 8 * t + 8)]) + ")",
}
DUCK = {
    "minute": lambda c, n: f"CAST(floor(epoch({c}) / {60 * n}) AS BIGINT)",
    "day": lambda c: f"strftime({c}, '%Y-%m-%d')",
    "words": lambda c: f"unnest(regexp_extract_all(lower({c}), '[a-z]+'))",
    "links": lambda c: rf"""unnest(regexp_extract_all({c}, 'href="([^"]*)"', 1))""",
    "signs": lambda c, t: "concat(" + ", ".join([f"'{t}:'"] + [f"CASE WHEN {c}[{i + 1}] >= 0 THEN '1' ELSE '0' END" for i in range(8 * t, 8 * t + 8)]) + ")",
}


def _basket(label: str, join: str, what: str = "l_partkey") -> str:
    return f"SELECT DISTINCT l_orderkey AS e, {what} AS v, {label} AS label FROM lineitem {join}"


def incidence_sql(name: str, d: dict) -> str:
    part = "JOIN part ON p_partkey = l_partkey"
    supplier = "JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey"
    words = lambda e, c, t, more="": f"SELECT DISTINCT e, v, CAST(length(v) AS VARCHAR(10)) AS label{more} FROM (SELECT {e} AS e, {d['words'](c)} AS v{more} FROM {t})"
    return {
        "basket_type": lambda: _basket("p_type", part),
        "basket_brand": lambda: _basket("p_brand", part),
        "basket_plain": lambda: _basket("''", ""),
        "supply_region": lambda: _basket("r_name", supplier, "l_suppkey"),
        "coactive_10m": lambda: f"SELECT DISTINCT {d['minute']('ts', 10)} AS e, user_id AS v, c_mktsegment AS label FROM events JOIN customer ON c_custkey = user_id",
        "coactive_1m": lambda: f"SELECT DISTINCT {d['minute']('ts', 1)} AS e, user_id AS v, c_mktsegment AS label FROM events JOIN customer ON c_custkey = user_id",
        "coactive_1h": lambda: f"SELECT DISTINCT {d['minute']('ts', 60)} AS e, user_id AS v, '' AS label FROM events",
        "customer_parts": lambda: f"SELECT DISTINCT o_custkey AS e, l_partkey AS v, p_brand AS label FROM orders JOIN lineitem ON l_orderkey = o_orderkey {part}",
        "supplier_parts": lambda: f"SELECT DISTINCT l_suppkey AS e, l_partkey AS v, p_type AS label FROM lineitem {part}",
        "doc_words": lambda: words("doc_id", "text", "documents"),
        "deal_typed": lambda: "SELECT DISTINCT e, v, label FROM (SELECT o_orderkey AS e, concat('C', CAST(o_custkey AS VARCHAR(20))) AS v, 'C' AS label FROM orders JOIN lineitem ON l_orderkey = o_orderkey UNION ALL SELECT l_orderkey, concat('P', CAST(l_partkey AS VARCHAR(20))), 'P' FROM lineitem UNION ALL SELECT l_orderkey, concat('S', CAST(l_suppkey AS VARCHAR(20))), 'S' FROM lineitem)",
        "props_day": lambda: f"SELECT DISTINCT concat(CAST(user_id AS VARCHAR(20)), ':', {d['day']('ts')}) AS e, props AS v, '' AS label FROM events WHERE props IS NOT NULL",
        "page_links": lambda: f"SELECT DISTINCT e, v, '' AS label FROM (SELECT page_id AS e, {d['links']('html')} AS v FROM pages)",
        "conv_words": lambda: words("conv_id", "text", "conversations"),
        "turn_words": lambda: f"SELECT DISTINCT e, v, CAST(length(v) AS VARCHAR(10)) AS label, elabel FROM (SELECT conv_id * 10000 + turn AS e, {d['words']('text')} AS v, role AS elabel FROM conversations)",
        "bench_words": lambda: words("item_id", "text", "benchmark"),
        "vec_buckets": lambda: " UNION ALL ".join(f"SELECT {d['signs']('embedding', t)} AS e, vec_id AS v, CAST(label AS VARCHAR(10)) AS label FROM embeddings" for t in range(8)),
        "nation_members": lambda: "SELECT n_nationkey AS e, concat('C', CAST(c_custkey AS VARCHAR(20))) AS v, c_mktsegment AS label FROM nation JOIN customer ON c_nationkey = n_nationkey UNION ALL SELECT n_nationkey, concat('S', CAST(s_suppkey AS VARCHAR(20))), 'S' FROM nation JOIN supplier ON s_nationkey = n_nationkey",
        "doc_quality": lambda: f"SELECT DISTINCT e, v, CAST(length(v) AS VARCHAR(10)) AS label, elabel FROM (SELECT documents.doc_id AS e, {d['words']('text')} AS v, concat(CAST(quality AS VARCHAR(2)), ':', CAST(toxic AS VARCHAR(2))) AS elabel FROM documents JOIN labels ON labels.doc_id = documents.doc_id)",
    }[name]()


NAMES = ("basket_type", "basket_brand", "basket_plain", "supply_region", "coactive_10m", "coactive_1h", "customer_parts", "supplier_parts", "doc_words", "deal_typed", "props_day", "page_links", "conv_words", "turn_words", "bench_words", "vec_buckets", "nation_members", "doc_quality")
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def incidence(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The rows of a carrier; tables are read by path."""
    sql = re.sub(r"\b(FROM|JOIN) (" + "|".join(TABLES) + r")\b", lambda m: f"{m[1]} parquet.`{sf_dir}/{m[2]}.parquet` AS {m[2]}", incidence_sql(name, SPARK))
    return spark.sql(sql)


def hypergraph(spark: SparkSession, sf_dir: str, name: str, simple: bool = True) -> HypergraphFrame:
    rows = incidence(spark, sf_dir, name)
    h = HypergraphFrame.from_incidence(rows, elabel="elabel" if "elabel" in rows.columns else None)
    return h.simplify() if simple else h


def edges_sql(name: str, simple: bool = True) -> str:
    """DuckDB: e, members (sorted list of vertices), labels (sorted), elabel; the same simplification, spelled as grouping."""
    base = incidence_sql(name, DUCK)
    named = "min(elabel)" if "elabel" in base.split("FROM")[0] else "CAST(NULL AS VARCHAR)"
    grouped = f"SELECT e, list_sort(list(v)) AS members, list_sort(list(label)) AS labels, {named} AS elabel, list_sort(list(concat(v, '\t', label))) AS tagged FROM ({base}) GROUP BY e"
    if not simple:
        return grouped
    return f"SELECT min(e) AS e, members, any_value(labels) AS labels, elabel, any_value(tagged) AS tagged FROM ({grouped}) WHERE len(members) > 1 GROUP BY members, elabel"
