"""The triangular matrix of pair counts, sparse or dense."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The dense triangle is used while its cells take at most this many bytes in a task.
DENSE_BYTES = 64 << 20
#: Cells of the full square up to which pairs are counted by a matrix product.
MATRIX_CELLS = 1 << 16


def cells(n: int) -> int:
    return n * (n - 1) // 2


def mode(n_items: int, max_value: int | None = None, by: str = "rank", budget: int = DENSE_BYTES) -> str:
    """`dense` if the triangle fits the budget, else `sparse`. by="value": sized by the largest item number, not by ranks."""
    size = cells(n_items if by == "rank" else (max_value or 0) + 1)
    return "dense" if 8 * size <= budget else "sparse"


def suffixes(encoded: DataFrame, array: str = "ranks") -> DataFrame:
    """(tid, first, rest): each element of a transaction with those after it; one row a position, no nested pair lists."""
    at = encoded.select("tid", F.col(array).alias("_all"), F.posexplode(array).alias("_pos", "first"))
    return at.select("tid", "first", F.slice("_all", F.col("_pos") + 2, F.size("_all")).alias("rest")).where(F.size("rest") > 0)


def count_sparse(encoded: DataFrame, min_count: int = 1, array: str = "ranks") -> DataFrame:
    """(i, j, support): pairs are counted in partial aggregates and spill if they must."""
    pairs = suffixes(encoded, array).select(F.col("first").alias("i"), F.explode("rest").alias("j"))
    return pairs.groupBy("i", "j").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= min_count)


def count_dense(encoded: DataFrame, n_items: int, min_count: int = 1) -> DataFrame:
    """The same through one numpy triangle a task; only its non-zero cells are shuffled."""
    cells_of = cells

    def run(batches):
        total = np.zeros(cells_of(n_items), np.int64)
        upper = np.triu_indices(n_items, 1) if n_items * n_items <= MATRIX_CELLS else None
        for b in batches:
            column = b.column(0)
            if len(column) and n_items * n_items <= MATRIX_CELLS:
                # Few items: the counts are the product of the 0/1 matrix with itself, exact in floats up to 2**24 rows.
                width = np.diff(np.asarray(column.offsets))
                cells = np.zeros((len(column), n_items), np.float32)
                cells[np.repeat(np.arange(len(width)), width), column.flatten().to_numpy(zero_copy_only=False)] = 1
                total += (cells.T @ cells)[upper].astype(np.int64)
                continue
            values, ends = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.asarray(column.offsets)[1:] - column.offsets[0].as_py()
            starts = np.r_[0, ends[:-1]]
            width = ends - starts
            # Every position is paired with those after it in its transaction.
            end_of = np.repeat(ends, width)
            n_after = end_of - np.arange(len(values)) - 1
            i = np.repeat(values, n_after)
            j = values[np.arange(n_after.sum()) - np.repeat(np.cumsum(n_after) - n_after, n_after) + np.repeat(np.arange(len(values)) + 1, n_after)]
            total += np.bincount(i * (2 * n_items - i - 1) // 2 + j - i - 1, minlength=len(total)) if len(i) else 0
        at = np.flatnonzero(total)
        i = (n_items - 2 - np.floor((np.sqrt(4.0 * n_items * (n_items - 1) - 8.0 * at - 7) - 1) / 2)).astype(np.int64)
        j = at + i + 1 - i * (2 * n_items - i - 1) // 2
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(total[at])], names=["i", "j", "support"])

    partial = encoded.select("ranks").mapInArrow(run, "i int, j int, support bigint")
    return partial.groupBy("i", "j").agg(F.sum("support").alias("support")).where(F.col("support") >= min_count)
