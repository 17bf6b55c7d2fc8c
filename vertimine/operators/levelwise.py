"""Level-wise mining: candidates of length k from the frequent sets of length k-1, counted by a scan of the transactions."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Candidates go to the tasks by broadcast up to this many; beyond it they are counted by a relational join.
BROADCAST_CANDIDATES = 200_000


def candidates(level: DataFrame) -> DataFrame:
    """(ranks) one longer: sets that agree in all but the last item are joined."""
    head = F.slice("ranks", 1, F.size("ranks") - 1)
    a = level.select(head.alias("head"), F.element_at("ranks", -1).alias("x"))
    b = level.select(head.alias("head"), F.element_at("ranks", -1).alias("y"))
    return a.join(b, "head").where("x < y").select(F.concat("head", F.array("x", "y")).alias("ranks"))


def prune(wanted: DataFrame, level: DataFrame, k: int) -> DataFrame:
    """Only candidates all of whose subsets one shorter are frequent."""
    if k <= 2:
        return wanted
    subsets = F.transform(F.sequence(F.lit(1), F.lit(k)), lambda i: F.concat(F.slice("ranks", F.lit(1), i - 1), F.slice("ranks", i + 1, F.lit(k))))
    rare = wanted.select("ranks", F.explode(subsets).alias("part")).join(level.select(F.col("ranks").alias("part")), "part", "left_anti").select("ranks").distinct()
    return wanted.join(rare, "ranks", "left_anti")


def count_scan(encoded: DataFrame, wanted: list[tuple[int, ...]], k: int) -> DataFrame:
    """(ranks, support): each task walks its transactions down a prefix tree of the candidates."""
    sent = encoded.sparkSession.sparkContext.broadcast(wanted)

    def run(batches):
        tree: dict = {}
        for n, c in enumerate(sent.value):
            node = tree
            for x in c[:-1]:
                node = node.setdefault(x, {})
            node[c[-1]] = n
        counts = [0] * len(sent.value)

        def walk(node, items, depth):
            if depth == 1:
                for x in items:
                    n = node.get(x)
                    if n is not None:
                        counts[n] += 1
                return
            for at in range(len(items) - depth + 1):
                below = node.get(items[at])
                if below is not None:
                    walk(below, items[at + 1 :], depth - 1)

        for b in batches:
            for items in b.column(0).to_pylist():
                if len(items) >= k:
                    walk(tree, items, k)
        some = [n for n, c in enumerate(counts) if c]
        yield pa.RecordBatch.from_arrays([pa.array([list(sent.value[n]) for n in some], pa.list_(pa.int32())), pa.array([counts[n] for n in some], pa.int64())], names=["ranks", "support"])

    partial = encoded.select("ranks").mapInArrow(run, "ranks array<int>, support bigint")
    return partial.groupBy("ranks").agg(F.sum("support").alias("support"))


def count_join(encoded: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """The same as a relational join: a candidate is in a transaction if all k of its items meet it."""
    rows = encoded.select("tid", F.explode("ranks").alias("x"))
    met = rows.join(wanted.select("ranks", F.explode("ranks").alias("x")), "x").groupBy("tid", "ranks").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == k)
    return met.groupBy("ranks").agg(F.count(F.lit(1)).alias("support"))


def mine(encoded: DataFrame, singles: DataFrame, min_count: int, max_len: int | None = None) -> DataFrame:
    """(ranks, support) of length 2 and more. One scan a level; the driver holds one level's candidates up to the stated bound."""
    spark = encoded.sparkSession
    level, levels, k = singles.select(F.array("rank").alias("ranks"), "support"), [], 2
    while max_len is None or k <= max_len:
        wanted = prune(candidates(level), level, k)
        rows = [tuple(r["ranks"]) for r in wanted.limit(BROADCAST_CANDIDATES + 1).collect()]
        if not rows:
            break
        counted = count_scan(encoded, rows, k) if len(rows) <= BROADCAST_CANDIDATES else count_join(encoded, wanted, k)
        level = counted.where(F.col("support") >= min_count).persist()
        if level.isEmpty():
            break
        levels.append(level)
        k += 1
    if not levels:
        return spark.createDataFrame([], "ranks array<int>, support bigint")
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out
