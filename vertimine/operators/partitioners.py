"""Which partition mines which class. Rules over the class's number v are plain column expressions."""

from __future__ import annotations

import heapq

from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("per_class", "modulo", "reflect", "snake", "greedy", "hash")


def per_class(v: Column) -> Column:
    return v.cast("int")


def modulo(v: Column, p: int) -> Column:
    return F.pmod(v, F.lit(p)).cast("int")


def reflect(v: Column, p: int) -> Column:
    """The first p classes forward, all later blocks of p backward."""
    return F.when(v < p, v).otherwise(F.lit(p - 1) - F.pmod(v, F.lit(p))).cast("int")


def snake(v: Column, p: int) -> Column:
    """Every other block of p backward."""
    return F.when(F.pmod(F.floor(v / p), F.lit(2)) == 0, F.pmod(v, F.lit(p))).otherwise(F.lit(p - 1) - F.pmod(v, F.lit(p))).cast("int")


def greedy(weights: dict[int, float], p: int) -> dict[int, int]:
    """Heaviest class first to the lightest partition; ties go to the lower class and partition number."""
    load = [(0.0, i) for i in range(p)]
    out = {}
    for v, w in sorted(weights.items(), key=lambda x: (-x[1], x[0])):
        total, i = heapq.heappop(load)
        out[v] = i
        heapq.heappush(load, (total + w, i))
    return out


def column(kind: str, v: Column, p: int, weights: dict[int, float] | None = None) -> Column:
    if kind == "per_class":
        return per_class(v)
    if kind == "hash":
        return F.pmod(F.hash(v), F.lit(p)).cast("int")
    if kind == "greedy":
        place = greedy(weights or {}, p)
        size = max(place, default=0) + 1
        return F.coalesce(F.get(F.lit([place.get(i, i % p) for i in range(size)]), v.cast("int")), modulo(v, p)).cast("int")
    if kind not in KINDS:
        raise ValueError(f"partitioner is one of {KINDS}, not {kind}")
    return {"modulo": modulo, "reflect": reflect, "snake": snake}[kind](v, p)
