"""Mining by tid shards, for classes too large for one worker: each shard holds bitmaps of its own transactions and returns local
supports, which add up because shards are disjoint. One round a level; the data stays where it is."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import levelwise
from .bottomup import _lists, bitmaps

#: Candidates of a level that are sent to the tasks; more are counted by a join.
SENT_CANDIDATES = 1_000_000


def shard(encoded: DataFrame, shards: int) -> DataFrame:
    return encoded.select("ranks").repartition(shards)


def local_supports(sharded: DataFrame, wanted: list[tuple[int, ...]]) -> DataFrame:
    sent = sharded.sparkSession.sparkContext.broadcast(wanted)

    def run(batches):
        member, row, n = [], [], 0
        for b in batches:
            values, width = _lists(b.column(0))
            member.append(values)
            row.append(np.repeat(np.arange(len(width)), width) + n)
            n += len(width)
        if not n:
            return
        members, bits = bitmaps(np.concatenate(member), np.concatenate(row), n)
        place = {x: k for k, x in enumerate(members.tolist())}
        found, head, both = [], None, None
        for c in sent.value:  # candidates come in prefix order, so the last prefix's bitmap serves its neighbours
            if c[:-1] != head:
                head, at = c[:-1], [place.get(x) for x in c[:-1]]
                both = None if None in at else np.bitwise_and.reduce(bits[at], axis=0)
            last = place.get(c[-1])
            count = int(np.bitwise_count(both & bits[last]).sum(dtype=np.int64)) if both is not None and last is not None else 0
            if count:
                found.append((c, count))
        yield pa.RecordBatch.from_arrays([pa.array([list(c) for c, _ in found], pa.list_(pa.int32())), pa.array([s for _, s in found], pa.int64())], names=["ranks", "support"])

    partial = sharded.select("ranks").mapInArrow(run, "ranks array<int>, support bigint")
    return partial.groupBy("ranks").agg(F.sum("support").alias("support"))


def mine(encoded: DataFrame, pairs: DataFrame, min_count: int, shards: int, max_len: int | None = None, max_candidates: int = SENT_CANDIDATES, heads: DataFrame | None = None) -> DataFrame:
    """(ranks, support) of length 2 and more; pairs: (i, j, support), frequent. With `heads` (some of the pairs), only itemsets that start with one of
    them and are longer. Candidates beyond max_candidates a level are counted by a join, with the same result."""
    data = shard(encoded, shards).persist()
    every = pairs.select(F.array("i", "j").alias("ranks"), "support")
    level, levels, k = every, [every], 3
    if heads is not None:
        level, levels = heads.select(F.array("i", "j").alias("ranks"), "support"), []
    while max_len is None or k <= max_len:
        if heads is None:
            wanted = levelwise.prune(levelwise.candidates(level), level, k)
        elif k == 3:  # a head with every item that is frequent beside both of its items
            after = pairs.select(F.col("i").alias("y"), F.col("j").alias("z"))
            wanted = level.select(F.col("ranks")[0].alias("x"), F.col("ranks")[1].alias("y")).join(after, "y").join(pairs.select(F.col("i").alias("x"), F.col("j").alias("z")), ["x", "z"], "left_semi").select(F.array("x", "y", "z").alias("ranks"))
        else:  # sets with one head share it with their own kin only, so other subsets aren't looked at
            wanted = levelwise.candidates(level)
        wanted = wanted.persist()
        n = wanted.count()
        if n and n <= max_candidates:
            counted = local_supports(data, sorted(tuple(r["ranks"]) for r in wanted.collect()))
        elif n:
            counted = levelwise.count_join(data.withColumn("tid", F.monotonically_increasing_id()), wanted, k)
        else:
            wanted.unpersist()
            break
        level = counted.where(F.col("support") >= min_count).persist()
        empty = level.isEmpty()
        wanted.unpersist()
        if empty:
            break
        levels.append(level)
        k += 1
    data.unpersist()
    if not levels:
        return encoded.sparkSession.createDataFrame([], "ranks array<int>, support bigint")
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out
