"""Best-fit packing of token sequences by bin completion.

Pieces of at most `capacity` tokens are placed in sequences. Only the number of pieces of each length matters for how
many sequences are needed, so the search runs on the driver over at most `capacity` counts. It takes the longest piece
left, enumerates the undominated fillings of the room beside it, prunes those that waste more than the bound on the
number of sequences allows, and branches on each; a best-fit-decreasing solution is the incumbent that it has to beat.
Fillings are tried in order of waste with few departures from the first choice before many, at every depth alike, until
the bound is met, everything is tried, or the budget of steps is spent (None: no budget, an exact search). The plan
that results, rows of (length, first rank, repetitions, first sequence, offset), is applied to the pieces by their rank
within a length, on the executors.
"""

from __future__ import annotations

import base64
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import ranked, table, written

CAPACITY, END = 1024, 2
#: Nodes that the search visits at most, over fillings and branches together; beyond them the best found so far is used, which is never worse than best fit.
STEPS = 400_000
#: The one special string of the vocabulary (fixed value), an id in texts too, as `tokenizers` has it.
SPECIAL = {"<|endoftext|>": 50256}


def vocabulary_path(name: str = "byte_bpe_50k.tiktoken") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(maxsize=2)
def encoder(path: str):
    """The byte-level vocabulary read as ranks: the same ids as its tokenizers file gives."""
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(k): int(v) for k, v in (line.split() for line in f if line.strip())}
    return tiktoken.Encoding("byte-bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=SPECIAL)


def pieces_of(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32. A null text has only the closing id. Only documents over the capacity are cut; the first piece takes the remainder."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long"

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for batch in batches:
            out: list[tuple] = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = enc.encode(text.as_py() or "", allowed_special="all")
                ids.append(end)
                raw = np.asarray(ids, "<u4").tobytes()
                first = len(ids) % capacity or capacity
                at, k = 0, 0
                while at < len(ids):
                    n = first if k == 0 else capacity
                    out.append((doc_id, k, at, n, zlib.crc32(raw[4 * at : 4 * (at + n)])))
                    at, k = at + n, k + 1
            columns = list(zip(*out, strict=True)) or [()] * 5
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(cut, schema)


class _Stock:
    """Pieces left by length."""

    def __init__(self, counts: dict[int, int]):
        self.count = {k: v for k, v in counts.items() if v}
        self.sizes = sorted(self.count)

    def take(self, size: int, n: int) -> None:
        self.count[size] -= n
        if not self.count[size]:
            del self.count[size]
            self.sizes.pop(bisect_left(self.sizes, size))

    def put(self, size: int, n: int) -> None:
        if size not in self.count:
            self.count[size] = 0
            insort(self.sizes, size)
        self.count[size] += n

    def total(self) -> int:
        return sum(k * v for k, v in self.count.items())


def _best_fit(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit decreasing on counts: the longest piece first, each time the longest that still fits; equal sequences are made together."""
    stock, plan = _Stock(counts), []
    while stock.sizes:
        chosen, room, used = [], capacity, {}
        while room:
            i = bisect_left(stock.sizes, room + 1) - 1
            while i >= 0 and used.get(stock.sizes[i], 0) >= stock.count[stock.sizes[i]]:
                i -= 1
            if i < 0:
                break
            size = stock.sizes[i]
            n = min(room // size, stock.count[size] - used.get(size, 0))
            chosen += [size] * n
            used[size] = used.get(size, 0) + n
            room -= n * size
        times = min(stock.count[s] // n for s, n in used.items())
        plan.append((tuple(chosen), times))
        for s, n in used.items():
            stock.take(s, n * times)
    return plan


class _Spent(Exception):
    pass


class _Budget:
    def __init__(self, steps: int | None):
        self.left = steps

    def step(self) -> None:
        if self.left is not None:
            self.left -= 1
            if self.left < 0:
                raise _Spent


def _fillings(stock: _Stock, room: int, allowed: int, budget: _Budget) -> Iterator[tuple[int, ...]]:
    """Undominated fillings of the room that waste at most `allowed`, found from the longest pieces down.

    A filling that leaves room for another piece in stock is dominated, and so is one in which a piece could be swapped
    for a longer one in stock. What can't fill the room up to the allowed waste with all smaller pieces is not grown.
    The stock must not change between two fillings; the caller puts it back first.
    """
    sizes, count = list(stock.sizes), dict(stock.count)
    below = np.concatenate([[0], np.cumsum([x * count[x] for x in sizes])]).tolist()  # tokens of all shorter pieces

    def whole(room: int, chosen: dict[int, int]) -> bool:
        if any(chosen.get(x, 0) < count[x] for x in sizes[: bisect_left(sizes, room + 1)]):
            return False
        return not any(chosen.get(x, 0) < count[x] for c in chosen for x in sizes[bisect_left(sizes, c + 1) : bisect_left(sizes, c + room + 1)])

    def grow(end: int, room: int, chosen: dict[int, int]) -> Iterator[tuple[int, ...]]:
        """Fillings that add pieces of sizes[:end] to the chosen; a level for each length used."""
        budget.step()
        for i in range(min(end, bisect_left(sizes, room + 1)) - 1, -1, -1):
            if below[i + 1] < room - allowed:
                break
            for n in range(min(room // sizes[i], count[sizes[i]]), 0, -1):
                yield from grow(i, room - n * sizes[i], chosen | {sizes[i]: n})
        if room <= allowed and whole(room, chosen):
            yield tuple(x for x, n in chosen.items() for _ in range(n))

    yield from grow(len(sizes), room, {})


def complete_bins(counts: dict[int, int], capacity: int = CAPACITY, steps: int | None = STEPS) -> tuple[list[tuple[tuple[int, ...], int]], int]:
    """(plan, lower bound): plan lists the lengths of a sequence and how many such sequences are made; the fewest found.

    steps None: the search ends only with the fewest possible. With a budget the gap to the bound may be real or not.
    """
    incumbent = _best_fit(counts, capacity)
    size = lambda plan: sum(n for _, n in plan)
    tokens = sum(k * v for k, v in counts.items())
    bound = max(-(-tokens // capacity), sum(v for k, v in counts.items() if 2 * k > capacity))
    best, best_size = incumbent, size(incumbent)
    budget, stock = _Budget(steps), _Stock(counts)

    def choices(spare: int, departures: int) -> Iterator[tuple[tuple[int, ...], int, int]]:
        """(lengths, times, departures left) for the next sequences: the first filling as often as the stock allows, and, as a departure, once; then each other filling once."""
        nonlocal tried_all
        longest = stock.sizes[-1]
        stock.take(longest, 1)
        options = _fillings(stock, capacity - longest, spare, budget)
        choice = next(options, None)
        stock.put(longest, 1)
        if choice is None:
            return
        full = (longest, *choice)
        waste = capacity - sum(full)
        times = min(stock.count[x] // full.count(x) for x in set(full))
        times = min(times, spare // waste) if waste else times
        yield full, times, departures
        if not departures:
            tried_all &= times == 1 and next(options, None) is None
            return
        if times > 1:
            yield full, 1, departures - 1
        for choice in options:
            yield (longest, *choice), 1, departures - 1

    def search(spare: int, departures: int) -> list[tuple[tuple[int, ...], int]] | None:
        """A plan that wastes at most `spare` tokens and departs from the first choice at most so often; depth first, with a stack of its own."""
        plan: list[tuple[tuple[int, ...], int]] = []
        stack = [(choices(spare, departures), spare)]  # the choices of each plan entry, and of the one to come

        def undo() -> None:
            full, times = plan.pop()
            for x in full:
                stock.put(x, times)

        while stack:
            if len(plan) == len(stack):
                undo()
            options, room = stack[-1]
            chosen = next(options, None)
            if chosen is None:
                stack.pop()
                continue
            full, times, left = chosen
            for x in full:
                stock.take(x, times)
            plan.append((full, times))
            if not stock.sizes:
                done = list(plan)
                while plan:
                    undo()
                return done
            room -= (capacity - sum(full)) * times
            stack.append((choices(room, left), room))
        return None

    departures = 0
    try:
        while best_size > bound:
            tried_all = True
            found = search((best_size - 1) * capacity - tokens, departures)
            if found is not None:
                best, best_size, departures = found, size(found), 0
            elif tried_all:
                break
            else:
                departures += 1
    except _Spent:
        pass
    return best, bound


def placements(plan: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length: first ranks, first sequences and offsets of its runs, by rank."""
    runs: dict[int, list[tuple[int, int, int]]] = {}
    rank: dict[int, int] = {}
    sequence = 0
    for lengths, times in plan:
        at = 0
        for n in lengths:
            runs.setdefault(n, []).append((rank.get(n, 0), sequence, at))
            rank[n] = rank.get(n, 0) + times
            at += n
        sequence += times
    return {n: tuple(np.array(c, np.int64) for c in zip(*r, strict=True)) for n, r in runs.items()}


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """pieces (a written table with doc_id, piece, length) with sequence_id and offset. The plan has at most one run for each place in each kind of sequence; its kinds are bounded by the lengths, not by the rows."""
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    plan, _ = complete_bins(counts, capacity)
    runs = pieces.sparkSession.sparkContext.broadcast(placements(plan))
    ordered = ranked(pieces, "length", ["doc_id", "piece", "ids_crc32"], "_rank", rows=sum(counts.values()))
    names = [f.name for f in pieces.schema]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "_rank"))
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for n in np.unique(length):
                first, start, at = runs.value[int(n)]
                own = np.flatnonzero(length == n)
                k = np.searchsorted(first, rank[own], side="right") - 1
                sequence[own], offset[own] = start[k] + rank[own] - first[k], at[k]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(sequence), pa.array(offset)], names=[*names, "sequence_id", "offset"])

    return ordered.select(*names, "_rank").mapInArrow(place, schema)


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    pieces = written(pieces_of(docs, path or vocabulary_path(), capacity), "pieces")
    return pack(pieces, capacity)


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 1024 tokens."""
    return pack_documents(table(spark, sf_dir, "documents"))
