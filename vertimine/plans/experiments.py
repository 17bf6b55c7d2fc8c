"""The experiment workloads: pipelines over falling supports, matrix and stripping ablations, placement, cores, growth.

Each returns plain rows (dicts), so that they can be printed, compared or made a DataFrame.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from vertimine import measures, threshold
from vertimine.operators import encode, pairs
from vertimine.plans.mine import PIPELINES, MiningConfig, mine, prepare, weights
from vertimine.sources import baskets

#: Falling supports per view, the last being the lowest.
SUPPORTS = {
    "customer_brands": ("0.7", "0.6", "0.5"),
    "line_bins": ("0.3", "0.2", "0.1"),
    "line_attrs": ("0.1", "0.05", "0.02"),
    "user_day_types": ("0.1", "0.05", "0.02"),
    "order_brands": ("0.02", "0.005", "0.002"),
    "turn_words": ("0.3", "0.2", "0.15"),
    "doc_words": ("0.5", "0.4", "0.35"),
}


def _run(tx, pipeline: str, at: str, **options) -> dict:
    found: list[int] = []
    kept = []
    seconds = measures.timed(lambda: kept.append(mine(tx, pipeline, at, **options)))
    found.append(kept[0].count())
    kept[0].unpersist()
    return {"pipeline": pipeline, "min_support": at, "seconds": seconds, "itemsets": found[0]}


def variants(spark: SparkSession, sf_dir: str, views=tuple(SUPPORTS), pipelines=(*PIPELINES, "levelwise")) -> list[dict]:
    """Every pipeline on every view and support, with its speed-up over level-wise mining where that ran."""
    out = []
    for view in views:
        tx = baskets.VIEWS[view](spark, sf_dir)
        for at in SUPPORTS[view]:
            rows = [{"view": view, **_run(tx, p, at)} for p in pipelines]
            base = next((r["seconds"] for r in rows if r["pipeline"] == "levelwise"), None)
            out += [r | {"speedup": measures.speedup(base, r["seconds"]) if base else None} for r in rows]
    return out


def ablate(spark: SparkSession, sf_dir: str, view: str, at: str) -> list[dict]:
    """Matrix on and off, stripping on and off, tid lists by group, map and projection, prefixes of two items."""
    tx = baskets.VIEWS[view](spark, sf_dir)
    tries = {
        "matrix_on": {}, "matrix_off": {"matrix": False}, "by_group": {"layout": "group"}, "projected": {"layout": "project"},
        "prefix2": {"layout": "project", "prefix_len": 2}, "unstripped": {"strip": False, "layout": "group"}, "sharded": {"shards": 4},
    }
    return [{"view": view, "option": k, **_run(tx, "filtered_mod", at, **o)} for k, o in tries.items()]


def stripping(spark: SparkSession, sf_dir: str, view: str = "customer_parts", supports=("0.01", "0.017", "0.018", "0.0185", "0.02")) -> list[dict]:
    tx = baskets.VIEWS[view](spark, sf_dir)
    n = tx.count()
    return [{"view": view, "min_support": at, **measures.strip_reduction(tx, threshold.resolve(n, at)).first().asDict()} for at in supports]


def balance(spark: SparkSession, sf_dir: str, view: str, at: str, p: int = 10) -> list[dict]:
    """Largest over mean load of each placement."""
    tx = baskets.VIEWS[view](spark, sf_dir)
    prep = prepare(tx, MiningConfig(), at)
    found = pairs.count_sparse(encode.strip(tx.rows, prep.frequent, prep.n_items), prep.min_count).persist()
    out = [{"view": view, "kind": k, "imbalance": measures.imbalance(measures.partition_load(found, k, p, weights(found) if k == "greedy" else None), p)} for k in ("modulo", "reflect", "snake", "greedy", "hash")]
    found.unpersist()
    return out


def partitions(spark: SparkSession, sf_dir: str, view: str, at: str, counts=(1, 2, 4, 8, 10, 16)) -> list[dict]:
    tx = baskets.VIEWS[view](spark, sf_dir)
    return [{"view": view, "p": p, **_run(tx, "filtered_mod", at, p=p)} for p in counts]


def growth(spark: SparkSession, sf_dir: str, view: str = "order_brands", at: str = "0.05", times=(1, 2, 4, 8, 16)) -> list[dict]:
    return [{"view": view, "times": r, **_run(baskets.replicated(baskets.VIEWS[view](spark, sf_dir), r, 10**12), "filtered_mod", at)} for r in times]


def matrix_sizes(spark: SparkSession, sf_dir: str, at: str = "0.002") -> list[dict]:
    """Cells by rank and by item number, as the items are and spread apart (number * 10000 + 7)."""
    tx = baskets.order_parts(spark, sf_dir)
    apart = baskets.Transactions(tx.rows.withColumn("item", (F.col("item").cast("bigint") * 10000 + 7).cast("string")), tx.transactions)
    least = threshold.resolve(tx.count(), at)
    return [{"items": name, **measures.matrix_cells(t, least).first().asDict()} for name, t in (("as they are", tx), ("spread", apart))]


#: View and support of each core-scaling run; the caller starts one session per number of cores.
CORES = {"line_bins": "0.1", "line_attrs": "0.02", "order_suppliers": "0.001", "order_brands": "0.002", "turn_words": "0.1"}


def cores(spark: SparkSession, sf_dir: str, pipelines=tuple(PIPELINES)) -> list[dict]:
    used = spark.sparkContext.defaultParallelism
    return [{"view": v, "cores": used, **_run(baskets.VIEWS[v](spark, sf_dir), p, at)} for v, at in CORES.items() for p in pipelines]
