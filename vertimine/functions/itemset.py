"""Functions over item arrays, as columns, Arrow functions, an aggregate and table functions."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertimine.operators.bottomup import mine_class


def contains_all(items: Column, wanted: Column) -> Column:
    """True if every wanted item is among the items; null items are ignored."""
    return F.size(F.array_except(F.filter(wanted, lambda x: x.isNotNull()), items)) == 0


def strip_udf(ranks: dict[str, int]):
    """Arrow function: items to ascending ranks of the known ones. The dictionary travels with the function."""

    @F.pandas_udf(T.ArrayType(T.IntegerType()))
    def strip(items: pd.Series) -> pd.Series:
        return items.map(lambda xs: [] if xs is None else sorted({ranks[x] for x in xs if x in ranks}))

    return strip


def tidset(tid: Column) -> Column:
    """Aggregate: the distinct tids of a group, ascending. One array a group: for groups that fit a row."""
    return F.sort_array(F.collect_set(tid))


def mined(rows: dict, names: list, least: int) -> list:
    """Frequent itemsets of items (name -> set of row numbers), in the order of `names`: (names, support)."""
    width = -(-(1 + max((max(x) for x in rows.values() if x), default=0)) // 64) * 64
    cells = np.zeros((len(names), width), bool)
    for r, x in enumerate(names):
        cells[r, list(rows[x])] = True
    return [([names[r] for r in items], n) for items, n in mine_class(np.arange(len(names)), np.packbits(cells, axis=1).view(np.uint64), least)]


@F.pandas_udf(T.LongType())
def tidset_count(tids: pd.Series) -> int:
    """Aggregate: number of distinct tids."""
    return int(tids.nunique())


@F.pandas_udf(T.BinaryType())
def tidset_and(a: pd.Series, b: pd.Series) -> pd.Series:
    """Bitwise and of two bitmaps; the shorter one counts as zero beyond its end."""
    return pd.Series([None if x is None or y is None else bytes(p & q for p, q in zip(x, y)) for x, y in zip(a, b)])


@F.udtf(returnType=T.StructType([T.StructField("itemset", T.StringType()), T.StructField("k", T.IntegerType()), T.StructField("support", T.LongType())]), useArrow=False)
class FrequentItemsets:
    """frequent_itemsets(TABLE(tid, item), least): all itemsets of one group of rows, mined in one process.

    Rows come one at a time; the group's state is reset by a new instance.
    """

    def __init__(self):
        self.tids, self.rows, self.least = {}, {}, 1

    def eval(self, row, least: int):
        self.least = least
        if row["item"] is not None:
            t = self.tids.setdefault(row["tid"], len(self.tids))
            self.rows.setdefault(row["item"], set()).add(t)

    def terminate(self):
        names = sorted(self.rows, key=lambda x: (len(self.rows[x]), x))
        for items, n in mined(self.rows, names, self.least):
            yield "|".join(sorted(items)), len(items), n


@F.udtf(returnType=T.StructType([T.StructField("itemset", T.StringType()), T.StructField("k", T.IntegerType()), T.StructField("support", T.LongType())]), useArrow=False)
class MineClass:
    """mine_class(TABLE(prefix, member, tid) PARTITION BY prefix, least): itemsets of one class, the prefix being one item."""

    def __init__(self):
        self.prefix, self.tids, self.rows, self.least = None, {}, {}, 1

    def eval(self, row, least: int):
        self.prefix, self.least = row["prefix"], least
        t = self.tids.setdefault(row["tid"], len(self.tids))
        self.rows.setdefault(row["member"], set()).add(t)

    def terminate(self):
        names = sorted(self.rows)
        for items, n in mined(self.rows, names, self.least):
            found = sorted([self.prefix, *items])
            yield "|".join(found), len(found), n


@F.udtf(returnType=T.StructType([T.StructField("itemset", T.StringType()), T.StructField("k", T.IntegerType())]), useArrow=False)
class Subsets:
    """subsets(items, k): the subsets of k of a transaction's distinct items, null items left out."""

    def eval(self, items: list, k: int):
        for c in combinations(sorted({x for x in items or () if x is not None}), k):
            yield "|".join(c), k


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udtf.register("frequent_itemsets", FrequentItemsets)
    spark.udtf.register("mine_class", MineClass)
    spark.udtf.register("subsets", Subsets)
    spark.udf.register("tidset_and", tidset_and)
    spark.udf.register("tidset_count", tidset_count)


__all__ = ["FrequentItemsets", "MineClass", "Subsets", "contains_all", "mined", "register", "strip_udf", "tidset", "tidset_and", "tidset_count"]
