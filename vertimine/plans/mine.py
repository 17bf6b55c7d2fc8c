"""Pipelines: which modules, in which order, mine a set of transactions."""

from __future__ import annotations

import contextlib
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertimine import threshold
from vertimine.operators import bottomup, chunks, classes, encode, items, levelwise, pairs, partitioners, reference, sharded
from vertimine.sources.baskets import Transactions

#: Bytes of one class's bitmaps that a task may hold. Larger classes are split into those of longer prefixes, and mined by tid shards if these are too large as well.
CLASS_BYTES = 256 << 20
#: Frequent pairs that are sent to all tasks (8 bytes each); more of them are joined by shuffle.
SENT_PAIRS = 2_000_000


@dataclass(frozen=True)
class MiningConfig:
    """strip: drop infrequent items first. layout: `map` or `group` (tid bitmaps by chunk, made in place or by a shuffle), or `project` (suffixes of
    transactions). matrix: count pairs before intersecting (True, False or "auto"); matrix_by: size it by `rank` or by the largest item number
    (`value`). prefix_len: length of the classes' prefixes. shards: mine everything by so many tid shards."""

    strip: bool = True
    layout: str = "map"
    matrix: bool | str = True
    matrix_by: str = "rank"
    partitioner: str = "modulo"
    p: int = 10
    prefix_len: int = 1
    order: str = "support_asc"
    max_len: int | None = None
    include_singletons: bool = True
    shards: int = 0
    class_bytes: int = CLASS_BYTES


PIPELINES = {
    "plain": MiningConfig(strip=False, layout="group", partitioner="per_class"),
    "filtered": MiningConfig(layout="group", partitioner="per_class"),
    "filtered_map": MiningConfig(layout="map", partitioner="per_class"),
    "filtered_mod": MiningConfig(layout="map", partitioner="modulo"),
    "filtered_reflect": MiningConfig(layout="map", partitioner="reflect"),
}


@dataclass
class Prepared:
    """What all stages share: counts on the driver are |D|, the threshold and n; everything else is a table."""

    n_transactions: int
    min_count: int
    frequent: DataFrame
    n_items: int
    arrays: DataFrame | None = None
    encoded: DataFrame | None = None
    kept: list[DataFrame] = field(default_factory=list)

    def keep(self, df: DataFrame) -> DataFrame:
        self.kept.append(df.persist())
        return df

    def release(self) -> None:
        for df in self.kept:
            df.unpersist()
        self.kept.clear()


def prepare(tx: Transactions, config: MiningConfig, min_support=None, min_count: int | None = None) -> Prepared:
    """One pass builds the transactions' item lists, which all later passes read from memory or local disk."""
    prep = Prepared(0, 0, tx.rows, 0)
    prep.arrays = prep.keep(tx.arrays())
    n_lists = prep.arrays.count()
    prep.n_transactions = tx.transactions.count() if tx.transactions is not None else n_lists
    prep.min_count = threshold.resolve(prep.n_transactions, min_support, min_count)
    cores = tx.rows.sparkSession.sparkContext.defaultParallelism
    if prep.arrays.select(F.spark_partition_id().alias("p")).distinct().count() < cores:  # a source of few file parts: deal it out, once
        prep.arrays = prep.keep(prep.arrays.repartition(cores))
    counted = prep.arrays.select(F.explode("items").alias("item"))
    prep.frequent = prep.keep(items.rank(items.counts(counted, prep.min_count), config.order))
    prep.n_items = prep.frequent.count()
    return prep


def _encoded(prep: Prepared, config: MiningConfig) -> tuple[DataFrame, int]:
    """(ranks) of each transaction, and the number of ranks. Unstripped, infrequent items have the ranks after the frequent ones."""
    ranked, n = prep.frequent.select("item", "rank"), prep.n_items
    if not config.strip:
        others = prep.arrays.select(F.explode("items").alias("item")).distinct().join(ranked, "item", "left_anti")
        rest = prep.keep(items.rank(others.withColumn("support", F.lit(0)), "lexical").select("item", (F.col("rank") + n).alias("rank")))
        ranked, n = ranked.unionByName(rest), n + rest.count()
    if n <= encode.BROADCAST_ITEMS:
        known = ranked.toArrow()
        return encode.strip_lists(prep.arrays, known["item"].to_pylist(), known["rank"].to_numpy()), n
    rows = prep.arrays.select("tid", F.explode("items").alias("item"))
    return encode.strip(rows, ranked, n).select("ranks"), n


def frequent_pairs(prep: Prepared, config: MiningConfig, n_ranks: int) -> DataFrame:
    """(i, j, support) of frequent pairs: counted in the transactions (the matrix), or from the intersections of all tid lists."""
    matrix = config.matrix
    if matrix == "auto":  # on while the triangle over all counted items is small
        largest = prep.frequent.agg(F.max(F.expr("try_cast(item as bigint)"))).first()[0] if config.matrix_by == "value" else None
        matrix = pairs.mode(n_ranks, largest, "value" if largest is not None else "rank") == "dense"
    if matrix:
        dense = pairs.mode(n_ranks) == "dense"
        return pairs.count_dense(prep.encoded, n_ranks, prep.min_count) if dense else pairs.count_sparse(prep.encoded.withColumn("tid", F.lit(0)), prep.min_count)
    return chunks.pair_supports(prep.encoded, n_ranks, prep.min_count, None if config.strip else prep.n_items)


def mine(tx: Transactions, pipeline: str = "auto", min_support=None, min_count: int | None = None, config: MiningConfig | None = None, **options) -> DataFrame:
    """All frequent itemsets: (items, k, support). pipeline: one of PIPELINES, `auto`, `levelwise`, or a config of your own.

    The itemsets are worked out at once and kept by Spark (unpersist() the result to let them go); whatever else was kept on the way is released."""
    if pipeline == "levelwise" and config is None:
        return mine_levelwise(tx, min_support, min_count, **options)
    if config is None:
        p = 3 * tx.rows.sparkSession.sparkContext.defaultParallelism
        config = MiningConfig(partitioner="greedy", p=p) if pipeline == "auto" else PIPELINES[pipeline]
    config = replace(config, **options)
    prep = prepare(tx, config, min_support, min_count)
    with contextlib.closing(_Closing(prep)):
        found = _mined(prep, config)
        out = bottomup.result(prep.frequent, found, prep.n_items, config.include_singletons).persist()
        out.count()
        return out


class _Closing:
    def __init__(self, prep: Prepared):
        self.close = prep.release


def _mined(prep: Prepared, config: MiningConfig) -> DataFrame:
    """(ranks, support) of two items and more."""
    spark = prep.frequent.sparkSession
    nothing = spark.createDataFrame([], bottomup.SCHEMA)
    if prep.n_items < 2 or config.max_len == 1:
        return nothing
    encoded, n_ranks = _encoded(prep, config)
    prep.encoded = prep.keep(encoded)
    found = prep.keep(frequent_pairs(prep, config, n_ranks))
    n_pairs = found.count()
    if not n_pairs:
        return nothing
    if config.shards:
        return sharded.mine(prep.encoded, found, prep.min_count, config.shards, config.max_len)
    if config.layout == "project" or config.prefix_len > 2 or n_pairs > SENT_PAIRS:
        return _projected(prep, config, found, n_pairs)
    table = found.toArrow()
    i, j, support = (table[c].to_numpy() for c in ("i", "j", "support"))
    allowed = chunks.Allowed.of(i, j, n_ranks)
    short, long, huge = split(allowed, i, j, support, supports(prep), config)
    levels = []
    if long or huge:  # itemsets of two that no class with a longer prefix gives
        split_heads = sorted({x for x, _ in [*long, *huge]})
        levels.append(found.join(F.broadcast(spark.createDataFrame([(x,) for x in split_heads], "i int")), "i").select(F.array("i", "j").alias("ranks"), "support"))
    prefixes = [(x,) for x in short] + long
    if prefixes:
        size = {p: len(allowed.members(p)) for p in prefixes}
        prefixes = [p for p in prefixes if size[p]]
        layout = chunks.by_map(prep.encoded, prefixes, allowed, n_ranks) if config.layout == "map" else chunks.by_group(prep.encoded, prefixes, allowed, n_ranks, None if config.strip else prep.n_items)
        p = max(prep.n_items - 1, 1) if config.partitioner == "per_class" else config.p
        work = {x[0]: 0.0 for x in prefixes}
        for x in prefixes:
            work[x[0]] += size[x] * (size[x] + 1) / 2
        pid = partitioners.column(config.partitioner, F.col("prefix")[0], p, work if config.partitioner == "greedy" else None)
        levels.append(bottomup.mine(layout, pid, p, prep.min_count, config.max_len))
    if huge:
        heads = spark.createDataFrame(huge, "i int, j int")
        at = found.join(F.broadcast(heads), ["i", "j"])
        shards = max(2, -(-int(support.max()) // (8 * config.class_bytes)) * 2)
        levels.append(sharded.mine(prep.encoded, found, prep.min_count, shards, config.max_len, heads=at))
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def supports(prep: Prepared) -> np.ndarray:
    told = prep.frequent.select("rank", "support").toArrow()
    out = np.zeros(prep.n_items, np.int64)
    out[told["rank"].to_numpy()] = told["support"].to_numpy()
    return out


def split(allowed: chunks.Allowed, i: np.ndarray, j: np.ndarray, support: np.ndarray, single: np.ndarray, config: MiningConfig) -> tuple[list[int], list[tuple[int, int]], list[tuple[int, int]]]:
    """(prefixes of one item, prefixes of two, prefixes of two that are too large as well), by the bytes of a class's bitmaps: a bit for each member and each
    row that has the prefix."""
    heads, m = np.unique(i, return_counts=True)
    large = (m * single[heads] / 8 > config.class_bytes) | (config.prefix_len == 2)
    long, huge = [], []
    for k in np.flatnonzero(np.isin(i, heads[large])):
        pair = (int(i[k]), int(j[k]))
        (huge if len(allowed.members(pair)) * support[k] / 8 > config.class_bytes else long).append(pair)
    return heads[~large].tolist(), long, huge


def _projected(prep: Prepared, config: MiningConfig, found: DataFrame, n_pairs: int) -> DataFrame:
    """Classes of transaction suffixes: needs no pairs on the driver, and prefixes of any length."""
    rows = prep.encoded.withColumn("tid", F.monotonically_increasing_id())
    made, extra = classes.project(rows, found, n_pairs), None
    for _ in range(config.prefix_len - 1):  # itemsets no longer than a prefix come from the classes it was grown from
        shorter = made.select("prefix", F.explode("suffix").alias("_m")).groupBy("prefix", "_m").agg(F.count(F.lit(1)).alias("support"))
        shorter = shorter.where(F.col("support") >= prep.min_count).select(F.concat("prefix", F.array("_m")).alias("ranks"), "support")
        extra = shorter if extra is None else extra.unionByName(shorter)
        made = classes.deepen(made, prep.min_count)
    p = max(prep.n_items - 1, 1) if config.partitioner == "per_class" else config.p
    kind = "hash" if config.partitioner == "greedy" and n_pairs > SENT_PAIRS else config.partitioner
    pid = partitioners.column(kind, F.col("prefix")[0], p, weights(found) if kind == "greedy" else None)
    mined = bottomup.mine(made, pid, p, prep.min_count, config.max_len)
    return mined if extra is None else mined.unionByName(extra)


def weights(frequent_pairs: DataFrame | None) -> dict[int, float]:
    """Work of a class: its members, plus the pairs of them. One row per frequent item reaches the driver."""
    if frequent_pairs is None:
        return {}
    return {r["i"]: r["n"] + r["n"] * (r["n"] - 1) / 2 for r in frequent_pairs.groupBy("i").agg(F.count(F.lit(1)).alias("n")).collect()}


def mine_levelwise(tx: Transactions, min_support=None, min_count: int | None = None, max_len: int | None = None, include_singletons: bool = True) -> DataFrame:
    prep = prepare(tx, MiningConfig(), min_support, min_count)
    with contextlib.closing(_Closing(prep)):
        prep.encoded = prep.keep(_encoded(prep, MiningConfig())[0])
        found = levelwise.mine(prep.encoded, prep.frequent, prep.min_count, max_len)
        out = bottomup.result(prep.frequent, found, prep.n_items, include_singletons).persist()
        out.count()
        return out


def mine_fpgrowth(tx: Transactions, min_support=None, min_count: int | None = None) -> DataFrame:
    n = tx.count()
    with_items = tx.rows.agg(F.count_distinct("tid").alias("n")).first()["n"]
    return reference.fpgrowth(tx.rows, with_items, threshold.resolve(n, min_support, min_count))


def explain_mining(tx: Transactions, pipeline: str = "auto", min_support=None, min_count: int | None = None) -> str:
    """What a pipeline would do: counts, the pair matrix, and how many classes have prefixes of one item, of two, or go to tid shards."""
    config = MiningConfig(partitioner="greedy", p=3 * tx.rows.sparkSession.sparkContext.defaultParallelism) if pipeline == "auto" else PIPELINES[pipeline]
    prep = prepare(tx, config, min_support, min_count)
    with contextlib.closing(_Closing(prep)):
        told = f"transactions {prep.n_transactions}, least count {prep.min_count}, frequent items {prep.n_items}, pair cells {pairs.cells(prep.n_items)} ({pairs.mode(prep.n_items)})"
        if prep.n_items > 1:
            encoded, n_ranks = _encoded(prep, config)
            prep.encoded = prep.keep(encoded)
            found = frequent_pairs(prep, config, n_ranks)
            if found.limit(SENT_PAIRS + 1).count() <= SENT_PAIRS:
                table = found.toArrow()
                i, j, support = (table[c].to_numpy() for c in ("i", "j", "support"))
                parts = split(chunks.Allowed.of(i, j, n_ranks), i, j, support, supports(prep), config)
                told += f"\nfrequent pairs {len(i)}, classes by one item {len(parts[0])}, by two {len(parts[1])}, by tid shards {len(parts[2])}"
    return f"{told}\n{config}"
