"""Vertical layout by chunks: transactions are cut into chunks of a few thousand, and an item's tid list is a bitmap over a chunk's rows.

No item's tid list is ever one row, however often the item occurs. Prefix classes are made chunk by chunk: the bitmaps of a prefix's
members, restricted to the rows that have the prefix, are the tidset intersections of the class, and one exchange brings a class's chunks
together. Two layouts make the chunks: `by_map` where the transactions are, without any traffic; `by_group` by a shuffle of all
occurrences, grouped by chunk and item.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Transactions of a chunk, and cells of the 0/1 matrix that a chunk may have; wider chunks are cut further.
ROWS, CELLS = 8192, 32 << 20
CLASSES = "prefix array<int>, chunk bigint, n int, members array<int>, bits binary"


@dataclass
class Allowed:
    """Frequent pairs (i, j), i < j, in rows of i: what may stand in a class beside its prefix."""

    start: np.ndarray
    js: np.ndarray

    @classmethod
    def of(cls, i: np.ndarray, j: np.ndarray, n_items: int) -> Allowed:
        order = np.lexsort((j, i))
        return cls(np.searchsorted(i[order], np.arange(n_items + 1)), j[order].astype(np.int32))

    def members(self, prefix: tuple[int, ...]) -> np.ndarray:
        out = self.js[self.start[prefix[0]] : self.start[prefix[0] + 1]]
        for x in prefix[1:]:
            out = np.intersect1d(out[out > x], self.js[self.start[x] : self.start[x + 1]], assume_unique=True)
        return out


def occurrences(column) -> tuple[np.ndarray, np.ndarray, int]:
    """(item, row) of each occurrence in a column of item lists, and the number of rows."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    width = np.diff(np.asarray(column.offsets))
    return column.flatten().to_numpy(zero_copy_only=False), np.repeat(np.arange(len(width)), width), len(width)


def cut(item: np.ndarray, row: np.ndarray, n_rows: int):
    """Chunks (item, row, number of rows) of at most ROWS rows and CELLS cells."""
    todo = [(s, min(n_rows, s + ROWS)) for s in range(0, n_rows, ROWS)][::-1]
    while todo:
        low, high = todo.pop()
        a, b = np.searchsorted(row, (low, high))
        if high - low > 8 and len(np.unique(item[a:b])) * (high - low) > CELLS:
            middle = (low + high) // 2
            todo += [(middle, high), (low, middle)]
        elif a < b:
            yield item[a:b], row[a:b] - low, high - low


def matrix(item: np.ndarray, row: np.ndarray, n_rows: int, n_items: int) -> tuple[np.ndarray, np.ndarray]:
    """(place of each item or -1, 0/1 matrix of the items present by rows)."""
    present = np.unique(item)
    place = np.full(n_items, -1, np.int32)
    place[present] = np.arange(len(present))
    cells = np.zeros((len(present), n_rows), bool)
    cells[place[item], row] = True
    return place, cells


def classes_of(place: np.ndarray, cells: np.ndarray, prefixes: list[tuple[int, ...]], allowed: Allowed):
    """(prefix, rows with it, members, bitmaps over these rows) of one chunk."""
    for prefix in prefixes:
        at = place[list(prefix)]
        if (at < 0).any():
            continue
        members = allowed.members(prefix)
        members = members[place[members] >= 0]
        if not len(members):
            continue
        rows = np.flatnonzero(cells[at].all(0))
        if not len(rows):
            continue
        found = cells[place[members]][:, rows]
        some = found.any(1)
        if some.any():
            yield prefix, len(rows), members[some], np.packbits(found[some], axis=1)


class _Out:
    """Rows of classes, gathered into batches."""

    def __init__(self):
        self.rows, self.size = [], 0

    def add(self, chunk, prefix, n, members, bits):
        self.rows.append((prefix, chunk, n, members, bits.tobytes()))
        self.size += bits.nbytes + 64

    def flush(self):
        prefix, chunk, n, members, bits = zip(*self.rows)
        self.rows, self.size = [], 0
        yield pa.RecordBatch.from_arrays(
            [pa.array([list(x) for x in prefix], pa.list_(pa.int32())), pa.array(chunk, pa.int64()), pa.array(n, pa.int32()), pa.array(members, pa.list_(pa.int32())), pa.array(bits, pa.binary())],
            names=["prefix", "chunk", "n", "members", "bits"],
        )


def by_map(encoded: DataFrame, prefixes: list[tuple[int, ...]], allowed: Allowed, n_items: int) -> DataFrame:
    """CLASSES from (ranks): chunks are batches of the tasks that hold the transactions."""
    sent = encoded.sparkSession.sparkContext.broadcast((prefixes, allowed))

    def run(batches):
        wanted, pairs = sent.value
        out, number = _Out(), TaskContext.get().partitionId() << 32
        for b in batches:
            for item, row, n in cut(*occurrences(b.column(0))):
                for found in classes_of(*matrix(item, row, n, n_items), wanted, pairs):
                    out.add(number, *found)
                number += 1
                if out.size > 8 << 20:
                    yield from out.flush()
        if out.rows:
            yield from out.flush()

    return encoded.select("ranks").mapInArrow(run, CLASSES)


def numbered(encoded: DataFrame) -> DataFrame:
    """(chunk, row, ranks): the place of each transaction."""

    def run(batches):
        number = TaskContext.get().partitionId() << 32
        for b in batches:
            for s in range(0, b.num_rows, ROWS):
                part = b.column(0).slice(s, ROWS)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), number)), pa.array(np.arange(len(part), dtype=np.int32)), part], names=["chunk", "row", "ranks"])
                number += 1

    return encoded.select("ranks").mapInArrow(run, "chunk bigint, row int, ranks array<int>")


def by_group(encoded: DataFrame, prefixes: list[tuple[int, ...]], allowed: Allowed, n_items: int, keep: int | None = None) -> DataFrame:
    """CLASSES from (ranks) by way of (chunk, rank, rows): one shuffled row per occurrence, then one per chunk and item.

    keep: ranks below it are kept after the lists have been gathered, for transactions that were not stripped."""
    sent = encoded.sparkSession.sparkContext.broadcast((prefixes, allowed))
    lists = numbered(encoded).select("chunk", "row", F.explode("ranks").alias("rank")).groupBy("chunk", "rank").agg(F.collect_list("row").alias("rows"))
    if keep is not None:
        lists = lists.where(F.size("rows") > 0).where(F.col("rank") < keep)

    def run(table: pa.Table) -> pa.Table:
        wanted, pairs = sent.value
        chunk, out = table.column("chunk")[0].as_py(), _Out()
        row, which, _ = occurrences(table.column("rows"))
        item = table.column("rank").to_numpy()[which]
        order = np.argsort(row, kind="stable")
        item, row = item[order], row[order]
        for found in (x for part in cut(item, row, int(row.max()) + 1) for x in classes_of(*matrix(*part, n_items), wanted, pairs)):
            out.add(chunk, *found)
        return pa.Table.from_batches(list(out.flush())) if out.rows else pa.table({f: pa.array([], t) for f, t in (("prefix", pa.list_(pa.int32())), ("chunk", pa.int64()), ("n", pa.int32()), ("members", pa.list_(pa.int32())), ("bits", pa.binary()))})

    return lists.groupBy("chunk").applyInArrow(run, CLASSES)


def pair_supports(encoded: DataFrame, n_items: int, min_count: int, keep: int | None = None) -> DataFrame:
    """(i, j, support) by intersecting every two tid lists, chunk by chunk: what building classes without a pair matrix has to do.

    keep: only ranks below it are frequent, so no other can be in a frequent pair, and their lists are not intersected."""

    def run(batches):
        total: dict[int, int] = {}
        keys, counts, waiting = [], [], 0
        for b in batches:
            item, row, n = occurrences(b.column(0))
            if keep is not None:
                item, row = item[item < keep], row[item < keep]
            for item, row, n in cut(item, row, n):
                present = np.unique(item)
                _, cells = matrix(item, row, n, n_items)
                bits = np.packbits(cells, axis=1)
                for k in range(len(present) - 1):
                    both = np.bitwise_count(bits[k + 1 :] & bits[k]).sum(1, dtype=np.int64)
                    some = np.flatnonzero(both)
                    keys.append(int(present[k]) * n_items + present[k + 1 :][some].astype(np.int64))
                    counts.append(both[some])
                    waiting += len(some)
                if waiting > 4 << 20:
                    yield from send(keys, counts, total)
                    keys, counts, waiting = [], [], 0
        if waiting:
            yield from send(keys, counts, total)

    def send(keys, counts, _):
        key, where = np.unique(np.concatenate(keys), return_inverse=True)
        n = np.bincount(where, np.concatenate(counts)).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array((key // n_items).astype(np.int32)), pa.array((key % n_items).astype(np.int32)), pa.array(n)], names=["i", "j", "support"])

    partial = encoded.select("ranks").mapInArrow(run, "i int, j int, support bigint")
    return partial.groupBy("i", "j").agg(F.sum("support").alias("support")).where(F.col("support") >= min_count)
