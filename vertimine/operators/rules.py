"""Association rules, maximal and closed itemsets, top-k."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def _others(itemsets: DataFrame) -> DataFrame:
    """Each itemset with each of its proper non-empty subsets: (items, k, support, part, rest)."""
    many = itemsets.where("k > 1").withColumn("mask", F.explode(F.expr("sequence(1, shiftleft(1, k) - 2)")))
    return many.withColumn("part", F.expr("filter(items, (x, i) -> (mask & shiftleft(1, i)) <> 0)")).withColumn("rest", F.expr("filter(items, (x, i) -> (mask & shiftleft(1, i)) = 0)")).drop("mask")


def generate(itemsets: DataFrame, min_conf: float, n_transactions: int, inclusive: bool = False, max_consequent: int | None = None) -> DataFrame:
    """antecedent, consequent, support, confidence, lift. Confidence must exceed min_conf (or reach it, if inclusive)."""
    split = _others(itemsets)
    if max_consequent is not None:
        split = split.where(F.size("rest") <= max_consequent)
    support = itemsets.select(F.col("items").alias("part"), F.col("support").alias("part_support"))
    goal = itemsets.select(F.col("items").alias("rest"), F.col("support").alias("rest_support"))
    conf = F.col("support").cast("double") / F.col("part_support")
    found = split.join(support, "part").withColumn("confidence", conf).where(F.col("confidence") >= min_conf if inclusive else F.col("confidence") > min_conf).join(goal, "rest")
    return found.select(
        F.array_join("part", "|").alias("antecedent"), F.array_join("rest", "|").alias("consequent"), "support", "confidence",
        (F.col("confidence") * n_transactions / F.col("rest_support")).alias("lift"),
    )


def _smaller(itemsets: DataFrame) -> DataFrame:
    """Each itemset's subsets one shorter, with the larger one's support: (items, above)."""
    drop_one = F.transform(F.sequence(F.lit(1), F.col("k")), lambda i: F.concat(F.slice("items", F.lit(1), i - 1), F.slice("items", i + 1, F.col("k"))))
    return itemsets.where("k > 1").select(F.explode(drop_one).alias("items"), F.col("support").alias("above"))


def maximal(itemsets: DataFrame) -> DataFrame:
    """Itemsets without a frequent superset."""
    return itemsets.join(_smaller(itemsets).select("items").distinct(), "items", "left_anti")


def closed(itemsets: DataFrame) -> DataFrame:
    """Itemsets without a superset of the same support."""
    best = _smaller(itemsets).groupBy("items").agg(F.max("above").alias("above"))
    return itemsets.join(best, "items", "left").where("above is null or above < support").drop("above")


def top_per_length(itemsets: DataFrame, n: int) -> DataFrame:
    """The n itemsets of highest support of each length; ties by text."""
    order = W.partitionBy("k").orderBy(F.col("support").desc(), F.array_join("items", "|"))
    return itemsets.withColumn("place", F.row_number().over(order)).where(F.col("place") <= n)
