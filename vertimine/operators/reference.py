"""Independent ways to the same answer, for tests and comparison."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import chunks, encode, items
from .bottomup import from_chunks, mine_class


def fpgrowth(rows: DataFrame, n_transactions: int, min_count: int) -> DataFrame:
    """MLlib's FP-growth; its threshold is a fraction, put half a transaction below the count."""
    from pyspark.ml.fpm import FPGrowth

    arrays = rows.groupBy("tid").agg(F.collect_list("item").alias("items"))
    found = FPGrowth(itemsCol="items", minSupport=max(0.0, (min_count - 0.5) / max(1, n_transactions))).fit(arrays).freqItemsets
    # MLlib counts only transactions that have items, so its own fraction is stricter or equal; the count decides.
    return found.where(F.col("freq") >= min_count).select(F.array_sort("items").alias("items"), F.size("items").alias("k"), F.col("freq").alias("support"))


def bruteforce(rows: DataFrame, min_count: int, max_width: int = 16) -> DataFrame:
    """Every non-empty subset of every transaction, counted. Transactions of up to max_width items only, else an error."""
    arrays = rows.groupBy("tid").agg(F.sort_array(F.collect_list("item")).alias("items"))
    fits = F.when(F.size("items") > max_width, F.raise_error(F.lit(f"a transaction has more than {max_width} items"))).otherwise(F.col("items"))
    masks = F.expr("sequence(1, shiftleft(1, size(items)) - 1)")
    chosen = arrays.select(fits.alias("items")).select("items", F.explode(masks).alias("mask"))
    subset = F.expr("filter(items, (x, i) -> (mask & shiftleft(1, i)) <> 0)")
    return chosen.select(subset.alias("items")).groupBy("items").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= min_count).select("items", F.size("items").alias("k"), "support")


def mine_local(transactions: dict, min_count: int, max_len: int | None = None) -> dict[tuple, int]:
    """One process, the whole lattice as one class with an empty prefix. transactions: tid -> items."""
    having: dict = {}
    for n, items in enumerate(transactions.values()):
        for x in {i for i in items if i is not None}:
            having.setdefault(x, []).append(n)
    ranked = sorted(having, key=lambda x: (len(having[x]), x))
    cells = np.zeros((len(ranked), -(-len(transactions) // 64) * 64), bool)
    for r, x in enumerate(ranked):
        cells[r, having[x]] = True
    found = mine_class(np.arange(len(ranked)), np.packbits(cells, axis=1).view(np.uint64), min_count, max_len)
    return {tuple(sorted(ranked[r] for r in items)): n for items, n in found}


def mine_sequential(arrays: DataFrame, min_count: int, max_len: int | None = None) -> dict[tuple, int]:
    """The same for a table (tid, items): the driver mines alone, and gets the frequent items' bitmaps (a bit a transaction and item) in place of transactions."""
    known = items.rank(items.counts(arrays.select(F.explode("items").alias("item")), min_count)).select("item", "rank").orderBy("rank").toArrow()
    names, n_items = known["item"].to_pylist(), known.num_rows
    if not names:
        return {}

    def run(batches):
        for b in batches:
            for item, row, n in chunks.cut(*chunks.occurrences(b.column(0))):
                place, cells = chunks.matrix(item, row, n, n_items)
                own = pa.array([np.flatnonzero(place >= 0).astype(np.int32)], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([pa.array([n], pa.int32()), own, pa.array([np.packbits(cells, axis=1).tobytes()], pa.binary())], names=["n", "members", "bits"])

    encoded = encode.strip_lists(arrays, names, known["rank"].to_numpy())
    found = mine_class(*from_chunks(encoded.mapInArrow(run, "n int, members array<int>, bits binary").toArrow()), min_count, max_len)
    return {tuple(sorted(names[r] for r in ranks)): n for ranks, n in found}
