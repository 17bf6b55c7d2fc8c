"""Transactions as ascending arrays of item ranks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Dictionaries of at most this many items are broadcast; larger ones are joined by shuffle.
BROADCAST_ITEMS = 1_000_000


def dictionary(ranked: DataFrame, n_items: int) -> DataFrame:
    side = ranked.select("item", "rank")
    return F.broadcast(side) if n_items <= BROADCAST_ITEMS else side


def strip(rows: DataFrame, ranked: DataFrame, n_items: int) -> DataFrame:
    """Drops infrequent items and emptied transactions: (tid, ranks). One shuffle, by tid."""
    kept = rows.join(dictionary(ranked, n_items), "item")
    return kept.groupBy("tid").agg(F.sort_array(F.collect_list("rank")).alias("ranks"))


def full(rows: DataFrame) -> DataFrame:
    """Nothing stripped: (tid, items) with all items, sorted."""
    return rows.groupBy("tid").agg(F.sort_array(F.collect_list("item")).alias("items"))


def _known(column: pa.Array, items: pa.Array, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ranks ascending within each row, ends of the rows) of a column of item lists; items without a rank are dropped."""
    width = np.diff(np.asarray(column.offsets))
    place = pc.index_in(column.flatten(), items)
    row = np.repeat(np.arange(len(width)), width)
    some = np.asarray(pc.is_valid(place))
    rank, row = ranks[place.drop_null().to_numpy()], row[some]
    order = np.lexsort((rank, row))
    return rank[order].astype(np.int32), np.cumsum(np.bincount(row, minlength=len(width)))


def strip_lists(arrays: DataFrame, items: list, ranks: np.ndarray) -> DataFrame:
    """(ranks) of (tid, items) lists without a shuffle: whole Arrow batches against a dictionary that the caller has checked for size."""
    sent = arrays.sparkSession.sparkContext.broadcast((pa.array(items), ranks))

    def run(batches):
        for b in batches:
            names, own = sent.value
            rank, ends = _known(b.column(0), names.cast(b.column(0).type.value_type), own)
            width = np.diff(np.r_[0, ends])
            offsets = np.r_[0, ends[width > 0]].astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(offsets), pa.array(rank))], names=["ranks"])

    return arrays.select("items").mapInArrow(run, "ranks array<int>")


def strip_arrays(transactions: DataFrame, ranks: dict) -> DataFrame:
    """The same for (tid, items) arrays, without a shuffle: Arrow batches against a broadcast dictionary."""
    sent = transactions.sparkSession.sparkContext.broadcast(ranks)

    def run(batches):
        known = sent.value
        for b in batches:
            out = [sorted({known[x] for x in items or () if x in known}) for items in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.list_(pa.int32()))], names=["tid", "ranks"])

    return transactions.select("tid", "items").mapInArrow(run, "tid bigint, ranks array<int>").where(F.size("ranks") > 0)
