"""Cost measures: reduction by stripping, load of partitions, matrix size, candidates, profiles, times."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertimine.operators import items, partitioners
from vertimine.sources.baskets import Transactions


def profile(tx: Transactions) -> DataFrame:
    """transactions, items, occurrences, mean_width, max_width in one row."""
    width = tx.rows.groupBy("tid").agg(F.count(F.lit(1)).alias("w"))
    return width.agg(F.sum("w").alias("occurrences"), F.max("w").alias("max_width")).join(tx.rows.agg(F.count_distinct("item").alias("items")), F.lit(True)).select(
        F.lit(tx.count()).cast("bigint").alias("transactions"), "items", "occurrences", "max_width", (F.col("occurrences") / F.lit(max(1, tx.count()))).alias("mean_width")
    )


def strip_reduction(tx: Transactions, min_count: int) -> DataFrame:
    """occ_before, occ_after, tx_before, tx_emptied, pct in one row: what dropping infrequent items saves."""
    frequent = items.counts(tx.rows, min_count)
    after = tx.rows.join(frequent.select("item"), "item", "left_semi").agg(F.count(F.lit(1)).alias("occ_after"), F.count_distinct("tid").alias("tx_after"))
    before = tx.rows.agg(F.count(F.lit(1)).alias("occ_before"), F.count_distinct("tid").alias("tx_before"))
    return before.join(after, F.lit(True)).select("occ_before", "occ_after", (F.col("tx_before") - F.col("tx_after")).alias("tx_emptied"), (F.lit(100.0) * (F.col("occ_before") - F.col("occ_after")) / F.col("occ_before")).alias("pct"))


def partition_load(pairs: DataFrame, kind: str, p: int, weights: dict | None = None) -> DataFrame:
    """pid, n_classes, members, pair_candidates of the 1-prefix classes that frequent pairs (i, j) make."""
    sizes = pairs.groupBy("i").agg(F.count(F.lit(1)).alias("m"))
    placed = sizes.withColumn("pid", partitioners.column(kind, F.col("i"), p, weights))
    return placed.groupBy("pid").agg(F.count(F.lit(1)).alias("n_classes"), F.sum("m").alias("members"), F.sum((F.col("m") * (F.col("m") - 1) / 2).cast("bigint")).alias("pair_candidates"))


def imbalance(load: DataFrame, p: int) -> float:
    """Largest over mean members of a partition; empty partitions count."""
    row = load.agg(F.max("members").alias("most"), F.sum("members").alias("all")).first()
    return row["most"] * p / row["all"] if row["all"] else 1.0


def matrix_cells(tx: Transactions, min_count: int, value: str | None = None) -> DataFrame:
    """cells_by_rank and cells_by_value (if items are numbers) of the pair triangle."""
    frequent = items.counts(tx.rows, min_count)
    n = F.count(F.lit(1))
    top = F.max(F.expr("try_cast(item as bigint)")) + 1
    return frequent.agg((n * (n - 1) / 2).cast("bigint").alias("cells_by_rank"), (top * (top - 1) / 2).cast("bigint").alias("cells_by_value"))


def by_length(itemsets: DataFrame) -> DataFrame:
    return itemsets.groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def support_of(rows: DataFrame, wanted: DataFrame, most_broadcast: int = 200_000) -> DataFrame:
    """Support of given itemsets (items) by one scan: an occurrence join on items, then a count of complete meetings.

    The itemsets are broadcast if there are at most most_broadcast of their items, else joined by shuffle."""
    asked = wanted.select("items", F.explode("items").alias("item"), F.size("items").alias("k")).persist()
    side = F.broadcast(asked) if asked.count() <= most_broadcast else asked
    met = rows.join(side, "item").groupBy("tid", "items", "k").agg(F.count(F.lit(1)).alias("n")).where("n = k")
    return met.groupBy("items").agg(F.count(F.lit(1)).alias("support"))


def intersections(tx: Transactions, min_count: int) -> DataFrame:
    """all_pairs, with_matrix, avoided: tidset intersections that building 1-prefix classes needs without and with the pair matrix."""
    from vertimine.operators import encode, pairs

    ranked = items.rank(items.counts(tx.rows, min_count)).persist()
    n = ranked.count()
    kept = pairs.count_sparse(encode.strip(tx.rows, ranked, n), min_count).agg(F.count(F.lit(1)).alias("with_matrix"))
    return kept.select(F.lit(pairs.cells(n)).cast("bigint").alias("all_pairs"), "with_matrix", (F.lit(pairs.cells(n)) - F.col("with_matrix")).cast("bigint").alias("avoided"))


def candidates(itemsets: DataFrame) -> DataFrame:
    """k, classes, candidates: pairs of k-itemsets that share all but the last item, i.e. candidates of length k + 1."""
    heads = itemsets.groupBy("k", F.slice("items", F.lit(1), F.col("k") - 1).alias("head")).agg(F.count(F.lit(1)).alias("m"))
    return heads.groupBy("k").agg(F.count(F.lit(1)).alias("classes"), F.sum((F.col("m") * (F.col("m") - 1) / 2).cast("bigint")).alias("candidates"))


def timed(run: Callable[[], object]) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def speedup(baseline: float, own: float) -> float:
    return baseline / own


def scans(tx: Transactions, run: Callable[[Transactions], DataFrame]) -> float:
    """How often `run` reads the transactions' lists from their source: rows that came out of it, over the rows there are."""
    spark = tx.rows.sparkSession
    lists = tx.arrays()
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    n = lists.count()
    watched = Transactions(tx.rows, tx.transactions, lists.mapInArrow(count, lists.schema), True)
    run(watched).count()
    return seen.value / max(1, n)


def stage_costs(spark, run: Callable[[], object]) -> dict[str, int]:
    """Bytes shuffled and spilled, and the largest peak of execution memory, over the stages that `run` starts."""
    store = spark.sparkContext._jsc.sc().statusStore()
    empty = spark.sparkContext._jvm.java.util.ArrayList()
    quantiles = spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0)

    def stages() -> dict:
        found = store.stageList(empty, False, False, quantiles, empty)
        return {(x.stageId(), x.attemptId()): x for x in (found.apply(k) for k in range(found.size()))}

    before = set(stages())
    run()
    new = [x for k, x in stages().items() if k not in before]
    return {
        "shuffle_bytes": sum(x.shuffleWriteBytes() for x in new), "spill_bytes": sum(x.diskBytesSpilled() for x in new),
        "peak_bytes": max((x.peakExecutionMemory() for x in new), default=0), "stages": len(new),
    }
