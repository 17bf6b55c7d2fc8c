"""Depth-first mining of prefix classes on tid bitmaps."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SCHEMA = "ranks array<int>, support bigint"
#: Words of 64 rows that an intersection looks at before it asks whether the rest can still reach the threshold.
STRIDE = 4096


def words(bits: np.ndarray) -> np.ndarray:
    """Bitmaps of bytes as 64-bit words, filled up with zeros."""
    short = -bits.shape[1] % 8
    return np.ascontiguousarray(np.pad(bits, ((0, 0), (0, short))) if short else bits).view(np.uint64)


def joined(own: np.ndarray, others: np.ndarray, min_count: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(places, supports, bitmaps) of the others whose intersection with `own` is frequent.

    Words in which `own` has no row are left out of the result. Wide bitmaps are looked at STRIDE words at a time, and an
    intersection is given up once it can't reach the threshold with all the rows of `own` that are left."""
    some = np.flatnonzero(own)
    if len(some) < 0.75 * len(own):
        own, others = own[some], others[:, some]
    alive, count = np.arange(len(others)), np.zeros(len(others), np.int64)
    if len(own) > STRIDE:
        left = int(np.bitwise_count(own).sum(dtype=np.int64))
        for s in range(0, len(own), STRIDE):
            part = own[s : s + STRIDE]
            count[alive] += np.bitwise_count(others[alive, s : s + STRIDE] & part).sum(1, dtype=np.int64)
            left -= int(np.bitwise_count(part).sum(dtype=np.int64))
            alive = alive[count[alive] + left >= min_count]
            if not len(alive):
                break
        return alive, count[alive], others[alive] & own
    both = others & own
    count = np.bitwise_count(both).sum(1, dtype=np.int64)
    alive = np.flatnonzero(count >= min_count)
    return alive, count[alive], both[alive]


def mine_class(items: np.ndarray, bits: np.ndarray, min_count: int, max_len: int | None = None, emit_atoms: bool = True) -> list[tuple[tuple[int, ...], int]]:
    """All frequent itemsets over the items (ascending; `bits`: a row of 64-bit words each), prefix left out: (items, support).

    Works off a stack. An entry is joined with those after it, and what stays frequent is worked off before the entry's next
    neighbour is touched: one list of bitmaps a level lives at once.
    """
    count = np.bitwise_count(bits).sum(1, dtype=np.int64)
    alive = count >= min_count
    items, bits, count = items[alive], bits[alive], count[alive]
    out = [((x,), n) for x, n in zip(items.tolist(), count.tolist())] if emit_atoms else []
    stack = [((), items, bits, 0)]
    while stack:
        head, level, rows, k = stack.pop()
        if k + 1 >= len(level) or max_len is not None and len(head) + 2 > max_len:
            continue
        stack.append((head, level, rows, k + 1))
        found, support, both = joined(rows[k], rows[k + 1 :], min_count)
        if not len(found):
            continue
        own, next_ = (*head, int(level[k])), level[k + 1 :][found]
        out += [((*own, x), n) for x, n in zip(next_.tolist(), support.tolist())]
        if len(next_) > 1:
            stack.append((own, next_, both, 0))
    return out


def bitmaps(member: np.ndarray, row: np.ndarray, n_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(items ascending, words) from occurrences: member k holds transaction number row[k] of the class."""
    order = np.argsort(member, kind="stable")
    member, row = member[order], row[order]
    first = np.flatnonzero(np.r_[True, member[1:] != member[:-1]]) if len(member) else np.zeros(0, int)
    bits = np.zeros((len(first), -(-n_rows // 64) * 8), np.uint8)
    for k, (s, e) in enumerate(zip(first, np.r_[first[1:], len(member)])):
        flags = np.zeros(n_rows, np.uint8)
        flags[row[s:e]] = 1
        packed = np.packbits(flags)
        bits[k, : len(packed)] = packed
    return member[first], bits.view(np.uint64)


def from_chunks(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """(items ascending, words) of one class from its chunks."""
    members = [x.as_py() for x in table.column("members")]
    width = -(-table.column("n").to_numpy() // 8)
    ends = np.cumsum(width)
    items = np.unique(np.concatenate(members)) if members else np.zeros(0, np.int32)
    bits = np.zeros((len(items), -(-int(ends[-1]) // 8) * 8 if len(ends) else 0), np.uint8)
    for own, packed, w, e in zip(members, table.column("bits"), width.tolist(), ends.tolist()):
        bits[np.searchsorted(items, own), e - w : e] = np.frombuffer(packed.as_buffer(), np.uint8).reshape(len(own), w)
    return items, bits.view(np.uint64)


def _lists(column) -> tuple[np.ndarray, np.ndarray]:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False), np.diff(np.asarray(column.offsets))


def mine(classes: DataFrame, pid, p: int, min_count: int, max_len: int | None = None) -> DataFrame:
    """(ranks, support) of all itemsets in the classes, atoms (prefix and one member) included.

    classes: (prefix, chunk, n, members, bits), (prefix, tid, suffix) or (prefix, member, tids). pid: partition of a class as a column, or None
    for Spark's own hash. One exchange places the classes; mining itself needs no more traffic.
    """
    kind = next(x for x in ("bits", "suffix", "tids") if x in classes.columns)
    keys = ["prefix"]
    if pid is not None:
        classes = classes.withColumn("pid", pid).repartitionById(p, "pid")
        keys = ["pid", "prefix"]

    def run(table: pa.Table) -> pa.Table:
        prefix = table.column("prefix")[0].as_py()
        room = None if max_len is None else max_len - len(prefix)
        found = []
        if room is None or room > 0:
            if kind == "bits":
                members, bits = from_chunks(table)
            elif kind == "suffix":
                member, width = _lists(table.column("suffix"))
                members, bits = bitmaps(member, np.repeat(np.arange(len(width)), width), len(width))
            else:
                tids, width = _lists(table.column("tids"))
                _, row = np.unique(tids, return_inverse=True)
                members, bits = bitmaps(np.repeat(table.column("member").to_numpy(), width), row, int(row.max()) + 1 if len(row) else 0)
            found = mine_class(members, bits, min_count, room)
        return pa.table({"ranks": pa.array([[*prefix, *items] for items, _ in found], pa.list_(pa.int32())), "support": pa.array([n for _, n in found], pa.int64())})

    columns = {"bits": ["n", "members", "bits"], "suffix": ["tid", "suffix"], "tids": ["member", "tids"]}[kind]
    return classes.select(*keys, *columns).groupBy(*keys).applyInArrow(run, SCHEMA)


def result(frequent: DataFrame, mined: DataFrame, n_items: int, include_singletons: bool = True) -> DataFrame:
    """(items, k, support) in item names: single items and mined itemsets."""
    names = frequent.select(F.col("rank").alias("_r"), F.col("item").alias("_i"))
    named = mined.select("ranks", "support", F.explode("ranks").alias("_r")).join(F.broadcast(names) if n_items <= 1_000_000 else names, "_r")
    sets = named.groupBy("ranks", "support").agg(F.array_sort(F.collect_list("_i")).alias("items")).select("items", F.size("items").alias("k"), "support")
    if not include_singletons:
        return sets
    return frequent.select(F.array("item").alias("items"), F.lit(1).alias("k"), "support").unionByName(sets)


def as_text(itemsets: DataFrame) -> DataFrame:
    return itemsets.select(F.array_join("items", "|").alias("itemset"), F.col("k").cast("int").alias("k"), F.col("support").cast("bigint").alias("support"))
