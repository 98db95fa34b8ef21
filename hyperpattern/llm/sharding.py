"""K-d tree sharding: space is split at distributed weighted medians along the widest dimension until every leaf is one shard.

A row is a point of integer metadata dimensions with a weight in bytes. A node with n shards is cut where n // 2 of n
parts of its weight lie on one side, along the dimension in which its rows spread widest relative to the whole table.
Cuts are found by refining histograms: every pass adds the weights of 4096 bins per node on the executors and narrows
each node to the one bin that holds its cut, so the driver sees bins, never rows. The points are a written table with a
column for the node they are in, which each level writes anew; what a pass looks for is a table of a row for each node.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import forget, ranked, table, text_or_empty, written

DIM_BITS, TIE_BITS, BIN_BITS = 20, 40, 12


@dataclass
class Node:
    shards: int
    first: int  # its shards are first .. first + shards - 1
    ident: int
    dim: int = 0
    cut: int = 0  # rows whose key in that dimension is below go left


def _scaled(dims: list[Column], bounds: list[tuple[int, int]]) -> list[Column]:
    """Each dimension as an integer of DIM_BITS bits over the range that the whole table spans."""
    top = (1 << DIM_BITS) - 1
    return [F.floor((d - lo) * F.lit(float(top)) / F.lit(float(max(1, hi - lo)))).cast("long") for d, (lo, hi) in zip(dims, bounds, strict=True)]


def _rows(spark: SparkSession, rows: list[tuple], names: list[str]) -> DataFrame:
    """A broadcast table of longs with a row for each node, at most one node a shard. Passes differ in its rows only, so their code is generated once."""
    values = ", ".join("(" + ", ".join(f"{x}L" for x in r) + ")" for r in rows)
    return F.broadcast(spark.sql(f"SELECT * FROM VALUES {values} AS t({', '.join(names)})"))


def _key(dims: int) -> Column:
    """The key in the dimension that the column _dim names."""
    out = F.col("_k0")
    for i in range(1, dims):
        out = F.when(F.col("_dim") == i, F.col(f"_k{i}")).otherwise(out)
    return out


def _widest(points: DataFrame, dims: int) -> dict[int, int]:
    """For each node, the dimension with the largest spread."""
    at = [F.shiftright(f"_k{i}", TIE_BITS) for i in range(dims)]
    spread = points.groupBy("_node").agg(*[(F.max(d) - F.min(d)).alias(f"_s{i}") for i, d in enumerate(at)]).collect()
    return {r["_node"]: max(range(dims), key=lambda i: (r[f"_s{i}"] or 0, -i)) for r in spread}


def _cuts(points: DataFrame, dims: int, todo: list[Node], weight: str) -> None:
    """Sets the cut of each node in todo: the bin boundary nearest to its share of weight, refined until the bin is slight or a single key."""
    state = {n.ident: {"lo": 0, "shift": DIM_BITS + TIE_BITS, "below": 0, "total": None} for n in todo}
    by_id = {n.ident: n for n in todo}
    while state:
        for s in state.values():
            s["shift"] = max(0, s["shift"] - BIN_BITS)
        asked = _rows(points.sparkSession, [(i, by_id[i].dim, s["lo"], s["shift"]) for i, s in state.items()], ["_node", "_dim", "_lo", "_shift"])
        near = points.join(asked, "_node").withColumn("_key", _key(dims))
        bins = near.selectExpr("_node", "shiftright(_key - _lo, cast(_shift as int)) AS _bin", f"`{weight}` AS _w").where(f"_bin >= 0 AND _bin < {1 << BIN_BITS}")
        sums: dict[int, list] = {}
        for r in bins.groupBy("_node", "_bin").agg(F.sum("_w").alias("w")).collect():
            sums.setdefault(r["_node"], []).append((r["_bin"], r["w"]))
        for i in list(state):
            s, n, got = state[i], by_id[i], sorted(sums.get(i, []))
            if s["total"] is None:
                s["total"] = sum(w for _, w in got)
            want, at, last = s["total"] * (n.shards // 2) / n.shards, s["below"], None
            for b, w in got:
                last = (b, w)
                if at + w >= want:
                    break
                at += w
            if last is None:
                n.cut = s["lo"]
                del state[i]
                continue
            b, w = last
            low = s["lo"] + (b << s["shift"])
            if s["shift"] == 0 or w <= s["total"] / n.shards / 4000:
                n.cut = low if want - at <= at + w - want else low + (1 << s["shift"])
                del state[i]
            else:
                s |= {"lo": low, "below": at}


def kd_tree(points: DataFrame, dims: int, weight: str, shards: int) -> DataFrame:
    """points (a written table with keys _k0 .. and _node 0) with the number of its leaf's shard in _node."""
    level, fresh = [Node(shards, 0, 0)], 1
    leaf: dict[int, int] = {0: 0}
    while level := [n for n in level if n.shards > 1]:
        widest = _widest(points, dims)
        for n in level:
            n.dim = widest.get(n.ident, 0)
        _cuts(points, dims, level, weight)
        below = []
        for n in level:
            half = n.shards // 2
            below += [Node(half, n.first, fresh), Node(n.shards - half, n.first + half, fresh + 1)]
            fresh += 2
        leaf |= {n.ident: n.first for n in below}
        cuts = _rows(points.sparkSession, [(n.ident, n.dim, n.cut, below[2 * j].ident, below[2 * j + 1].ident) for j, n in enumerate(level)], ["_node", "_dim", "_cut", "_low", "_high"])
        moved = points.join(cuts, "_node", "left").withColumn("_node", F.when(F.col("_dim").isNull(), F.col("_node")).when(_key(dims) < F.col("_cut"), F.col("_low")).otherwise(F.col("_high")))
        old, points = points, written(moved.select(*points.columns), "points")
        forget(old)
        level = below
    named = _rows(points.sparkSession, sorted(leaf.items()), ["_node", "_shard"])
    return points.join(named, "_node").withColumn("_node", F.col("_shard")).drop("_shard")


def assign_shards(points: DataFrame, dims: list[str], weight: str, group: str, unique: list[str], shards: int) -> DataFrame:
    """points with a column `shard` in 0 .. shards - 1, weights near equal.

    dims: long columns; weight: long column over 0; group: a long hash; rows of equal dims and group stay together,
    except groups over half a shard, which are told apart by the columns `unique`. Nulls in dims count as 0. Ties at a cut
    are broken by the hash of the group. An empty table gives an empty table. points: a written table, read once for the
    totals, once for heavy groups and once for the keys.
    """
    total = points.agg(F.sum(weight).alias("w"), *[f(F.coalesce(F.col(d), F.lit(0))).alias(f"{n}{i}") for i, d in enumerate(dims) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    if not total["w"]:
        return points.withColumn("shard", F.lit(0).cast("long"))
    # at most 2 * shards groups can be that heavy
    heavy = [r[0] for r in points.groupBy(group).agg(F.sum(weight).alias("w")).where(F.col("w") > total["w"] / shards / 2).select(group).collect()]
    mixed = F.xxhash64(group)
    tie = F.when(F.col(group).isin(heavy), F.xxhash64(group, *unique)).otherwise(mixed) if heavy else mixed
    tie = F.shiftrightunsigned(tie, 64 - TIE_BITS)
    scaled = _scaled([F.coalesce(F.col(d), F.lit(0)) for d in dims], [(total[f"lo{i}"], total[f"hi{i}"]) for i in range(len(dims))])
    keyed = points.withColumns({f"_k{i}": F.shiftleft(s, TIE_BITS) + tie for i, s in enumerate(scaled)} | {"_node": F.lit(0).cast("long")})
    out = kd_tree(written(keyed, "points"), len(dims), weight, shards)
    return out.withColumnRenamed("_node", "shard").drop(*[f"_k{i}" for i in range(len(dims))])


def op6_kd_tree_sharding(spark: SparkSession, sf_dir: str, shards: int = 24) -> DataFrame:
    """All documents in shards by the law `bytes`. Null text has no bytes; equal texts stay together unless their group is over half a shard; null ids and repeated rows are rows like others."""
    return shard_documents(table(spark, sf_dir, "documents"), shards)


def shard_documents(docs: DataFrame, shards: int = 24) -> DataFrame:
    """Dimensions are metadata that the text itself fixes (bytes, characters beyond ASCII, lines, spaces), so copies are one point."""
    text = text_or_empty()
    raw = F.octet_length(text)
    points = docs.select(
        "doc_id",
        (raw + 8).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
        F.xxhash64(text).alias("_group"),
        raw.cast("long").alias("_bytes"),
        (raw - F.char_length(text)).cast("long").alias("_wide"),
        (raw - F.octet_length(F.replace(text, F.lit("\n"), F.lit("")))).cast("long").alias("_lines"),
        (raw - F.octet_length(F.replace(text, F.lit(" "), F.lit("")))).cast("long").alias("_spaces"),
        F.monotonically_increasing_id().alias("_row"),  # fixed once written; tells repeated rows apart
    )
    out = assign_shards(written(points, "points"), ["_bytes", "_wide", "_lines", "_spaces"], "size", "_group", ["_row"], shards)
    out = ranked(written(out.select("doc_id", "size", "text_crc32", "shard", "_row"), "sharded"), "shard", ["doc_id", "_row"], "slot")
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))
