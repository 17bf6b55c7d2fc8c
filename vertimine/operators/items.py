"""Frequent single items: counted by ones or through their tid lists, and ranked."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

ORDERS = ("support_asc", "support_desc", "lexical")


def counts(rows: DataFrame, min_count: int = 1) -> DataFrame:
    """(item, support): partial counts before the shuffle, so at most tasks x items rows move."""
    return rows.groupBy("item").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= min_count)


def vertical_counts(rows: DataFrame, min_count: int = 1) -> DataFrame:
    """(item, tids, support): every (item, tid) pair moves; the list is the item's tidset."""
    return rows.groupBy("item").agg(F.sort_array(F.collect_list("tid")).alias("tids")).withColumn("support", F.size("tids").cast("bigint")).where(F.col("support") >= min_count)


def _order(order: str) -> list[Column]:
    if order not in ORDERS:
        raise ValueError(f"order is one of {ORDERS}, not {order}")
    return {"support_asc": [F.col("support"), F.col("item")], "support_desc": [F.col("support").desc(), F.col("item")], "lexical": [F.col("item")]}[order]


def rank(frequent: DataFrame, order: str = "support_asc") -> DataFrame:
    """Adds `rank`, 0 to n-1. The table holds frequent items only, never tids, so one sorted partition is enough."""
    return frequent.withColumn("rank", (F.row_number().over(W.orderBy(*_order(order))) - 1).cast("int"))
