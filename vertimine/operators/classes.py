"""Prefix classes: members with their tidsets (from a vertical layout), or transaction suffixes (from a horizontal one)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BROADCAST_PAIRS = 500_000


def build(vertical: DataFrame, min_count: int, n_items: int, pairs: DataFrame | None = None) -> DataFrame:
    """(prefix, member, tids): tid lists intersected for pairs that the matrix allows; without one, for all rank pairs.

    A pair's support is tested either way.
    """
    if pairs is None:
        wanted = vertical.where(F.col("rank") < n_items - 1).select(F.col("rank").alias("i"), F.explode(F.sequence(F.col("rank") + 1, F.lit(n_items - 1))).alias("j"))
    else:
        wanted = pairs.select("i", "j")
    a, b = vertical.select(F.col("rank").alias("i"), F.col("tids").alias("a")), vertical.select(F.col("rank").alias("j"), F.col("tids").alias("b"))
    joined = wanted.join(a, "i").join(b, "j").select(F.array("i").alias("prefix"), F.col("j").alias("member"), F.array_intersect("a", "b").alias("tids"))
    return joined.where(F.size("tids") >= min_count)


def project(encoded: DataFrame, pairs: DataFrame, n_pairs: int) -> DataFrame:
    """(prefix, tid, suffix): per transaction and rank the later ranks that are frequent with it. No intersection, no driver."""
    from .pairs import suffixes

    allowed = pairs.groupBy("i").agg(F.collect_list("j").alias("js"))
    allowed = F.broadcast(allowed) if n_pairs <= BROADCAST_PAIRS else allowed
    rows = suffixes(encoded).join(allowed, F.col("first") == F.col("i"))
    return rows.select(F.array("first").alias("prefix"), "tid", F.array_intersect("rest", "js").alias("suffix")).where(F.size("suffix") > 0)


def deepen(projected: DataFrame, min_count: int) -> DataFrame:
    """Classes one item deeper: the prefix grows by each member whose longer prefix is frequent."""
    at = projected.select("prefix", "tid", F.col("suffix").alias("_all"), F.posexplode("suffix").alias("_pos", "_next"))
    grown = at.select(F.concat("prefix", F.array("_next")).alias("prefix"), "tid", F.slice("_all", F.col("_pos") + 2, F.size("_all")).alias("suffix"))
    frequent = grown.groupBy("prefix").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= min_count).select("prefix")
    return grown.where(F.size("suffix") > 0).join(frequent, "prefix", "left_semi")


def members(pairs: DataFrame) -> DataFrame:
    """(prefix, members, support list) of the 1-prefix classes, straight from the pair matrix."""
    return pairs.groupBy(F.col("i").alias("prefix")).agg(F.sort_array(F.collect_list("j")).alias("members"))
