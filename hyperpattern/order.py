"""Which unmapped query edge a partial embedding maps next, as a sort key; the least key is chosen. Ties go to the lowest position."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .pattern import PatternGraph

ORDERS = ("dynamic", "degree", "candsize", "constraints", "fixed", "random")


def order_key(p: PatternGraph, order: str, q: Column, count: Column, mask: Column) -> Column:
    """dynamic: an edge with one candidate first, then most unmapped neighbours, then fewest candidates."""
    near = F.element_at(F.array(*[F.lit(a).cast("long") for a in p.adjacent]), q + 1)
    unmapped = F.bit_count(near.bitwiseAND(F.bitwise_not(mask)))
    mapped = F.bit_count(near.bitwiseAND(mask))
    parts = {
        "dynamic": [(count != 1).cast("int"), -unmapped, count],
        "degree": [-F.bit_count(near)],
        "candsize": [count],
        "constraints": [-mapped],
        "fixed": [],
        "random": [F.conv(F.substring(F.md5(q.cast("string")), 1, 8), 16, 10).cast("long")],
    }[order]
    return F.struct(*[x.cast("long").alias(f"k{i}") for i, x in enumerate([*parts, q])])


def static_order(p: PatternGraph, counts: list[int]) -> list[int]:
    """One order for all: the smallest candidate set first, then what touches what is mapped, smallest first."""
    left, out, reach = set(range(p.size)), [], 0
    while left:
        q = min(left, key=lambda x: (not (reach >> x & 1) if out else False, counts[x], x))
        out.append(q)
        left.remove(q)
        reach |= p.adjacent[q]
    return out
