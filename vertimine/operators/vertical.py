"""Horizontal transactions to tid lists per item, and back."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def by_group(encoded: DataFrame) -> DataFrame:
    """(rank, tids) by grouping: one shuffled row per occurrence."""
    return encoded.select("tid", F.explode("ranks").alias("rank")).groupBy("rank").agg(F.sort_array(F.collect_list("tid")).alias("tids"))


def by_map(encoded: DataFrame) -> DataFrame:
    """(rank, tids) through a map per task, then a merge: at most one shuffled row per task and item."""

    def run(batches):
        ranks, tids = [], []
        for b in batches:
            column = b.column(1)
            width = np.diff(np.asarray(column.offsets))
            ranks.append(column.flatten().to_numpy(zero_copy_only=False))
            tids.append(np.repeat(b.column(0).to_numpy(zero_copy_only=False), width))
        if not ranks or not sum(map(len, ranks)):
            return
        rank, tid = np.concatenate(ranks), np.concatenate(tids)
        order = np.argsort(rank, kind="stable")
        rank, tid = rank[order], tid[order]
        first = np.flatnonzero(np.r_[True, rank[1:] != rank[:-1]])
        lists = pa.ListArray.from_arrays(pa.array(np.r_[first, len(rank)].astype(np.int32)), pa.array(tid.astype(np.int64)))
        yield pa.RecordBatch.from_arrays([pa.array(rank[first].astype(np.int32)), lists], names=["rank", "tids"])

    partial = encoded.select("tid", "ranks").mapInArrow(run, "rank int, tids array<bigint>")
    return partial.groupBy("rank").agg(F.sort_array(F.flatten(F.collect_list("tids"))).alias("tids"))


def to_horizontal(vertical: DataFrame) -> DataFrame:
    return vertical.select("rank", F.explode("tids").alias("tid")).groupBy("tid").agg(F.sort_array(F.collect_list("rank")).alias("ranks"))
