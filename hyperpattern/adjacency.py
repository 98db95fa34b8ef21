"""Distinct pairs of vertices that share an edge, without a shuffle of pairs.

Vertices are dealt to tiles by hash. An edge travels once to every tile that holds one of its vertices, so what is shuffled
is edges times tiles, not pairs. A task makes the union of a vertex's edges in memory, one vertex after the other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Tiles: one for each SOME pairs up to TILES, then one for each MANY. Values that are sent in one batch.
SOME, TILES, MANY, SENT = 1 << 20, 64, 1 << 26, 1 << 20


def _spans(first: np.ndarray, length: np.ndarray) -> np.ndarray:
    """first[0], first[0] + 1, ... of all stretches, end to end."""
    return np.arange(length.sum()) + np.repeat(first - (np.cumsum(length) - length), length)


def _lists(values: pa.Array, length: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]).astype(np.int32)), values)


def _flat(column: pa.Array) -> tuple[pa.Array, np.ndarray]:
    return column.flatten(), pc.list_value_length(column).to_numpy(zero_copy_only=False).astype(np.int64)


def _deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(m, tile of each of m) of an edge: for each tile (tile, m, those of m in the tile)."""
    for batch in batches:
        m, length = _flat(batch.column(0))
        tile = batch.column(1).flatten().to_numpy()
        row = np.repeat(np.arange(len(length)), length)
        order = np.lexsort((tile, row))
        edge = np.flatnonzero((np.diff(row[order], prepend=-1) != 0) | (np.diff(tile[order], prepend=-1) != 0))
        first = np.cumsum(length) - length
        of, own = row[order[edge]], np.diff(np.append(edge, len(row)))
        size = np.cumsum(length[of])
        at = 0
        while at < len(of):
            end = max(at + 1, int(np.searchsorted(size, (size[at - 1] if at else 0) + SENT, side="right")))
            x = of[at:end]
            here = order[edge[at] : edge[at] + own[at:end].sum()]
            yield pa.RecordBatch.from_arrays([pa.array(tile[order[edge[at:end]]], pa.int32()), _lists(m.take(pa.array(_spans(first[x], length[x]))), length[x]), _lists(m.take(pa.array(here)), own[at:end])], names=["tile", "m", "own"])
            at = end


def _unions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(tile, m, own) of a partition: a of own and b of all its m, a < b, each pair once."""
    parts = [(*_flat(b.column(1)), *_flat(b.column(2))) for b in batches if b.num_rows]
    if not parts:
        return
    m, length, own, n_own = (pa.concat_arrays(x) if isinstance(x[0], pa.Array) else np.concatenate(x) for x in zip(*parts, strict=True))
    parts.clear()
    known = m.dictionary_encode()
    code, known = known.indices.to_numpy(), known.dictionary
    order = pc.sort_indices(known).to_numpy()
    rank = np.empty(len(order), np.int32)
    rank[order] = np.arange(len(order), dtype=np.int32)
    code, a = rank[code], rank[pc.index_in(own, value_set=known).to_numpy()]
    known = known.take(pa.array(order))
    last = np.cumsum(length)
    edge = np.repeat(np.arange(len(length)), n_own)
    by_a = np.argsort(a, kind="stable")
    a, edge = a[by_a], edge[by_a]
    bounds = np.append(np.flatnonzero(np.diff(a, prepend=-1)), len(a)).tolist()
    mark, held, n = np.zeros(len(known), bool), [], 0

    def batch() -> pa.RecordBatch:
        left = np.repeat([x for x, _ in held], [len(y) for _, y in held])
        return pa.RecordBatch.from_arrays([known.take(pa.array(left)), known.take(pa.array(np.concatenate([y for _, y in held])))], names=["a", "b"])

    for i, j in zip(bounds[:-1], bounds[1:], strict=True):
        v = a[i]
        members = [code[last[e] - length[e] : last[e]] for e in edge[i:j]]
        if sum(map(len, members)) * 8 < len(known):
            b = np.unique(np.concatenate(members))
            b = b[b > v]
        else:
            mark[v:] = False
            for x in members:
                mark[x] = True
            b = np.flatnonzero(mark[v + 1 :]) + v + 1
        held.append((v, b))
        n += len(b)
        if n >= SENT:
            yield batch()
            held, n = [], 0
    if n:
        yield batch()


def vertex_pairs(edges: DataFrame) -> DataFrame:
    """a < b of edges (members): vertices that share an edge."""
    size = F.size("members").cast("long")
    pairs = edges.agg(F.coalesce(F.sum(size * (size - 1) / 2), F.lit(0)).cast("long").alias("n")).first()["n"]
    tiles = max(1, min(TILES, pairs // SOME), pairs // MANY)
    v = edges.schema["members"].dataType.elementType["v"].dataType.simpleString()
    ids = edges.select(F.transform("members", lambda x: x["v"]).alias("m")).select("m", F.transform("m", lambda x: F.pmod(F.xxhash64(x), F.lit(tiles)).cast("int")).alias("tiles"))
    dealt = ids.mapInArrow(_deal, f"tile int, m array<{v}>, own array<{v}>").repartition(tiles, "tile")
    return dealt.mapInArrow(_unions, f"a {v}, b {v}")
