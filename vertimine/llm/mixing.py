"""Mixing sources to target weights by pivotal dependent rounding.

Each row of a source should be taken target / source_size times: a whole number of copies plus a fraction. Fractions are made
whole by pairing rows: in a pair, mass (words) moves at random from one row to the other until one of the two is whole,
with odds that keep every row's expected copies; the words taken in sum do not change. Rows are paired in buckets of a
few hundred rows; the one row of each source that a bucket leaves fractional goes up to the next level of that source's tree,
where the residuals of FAN buckets are paired again, and so on to the root. There one row of each source is left, often a long one, and is
rounded to the nearer whole number. What that misses by is made good by a reserve: up to RESERVE rows of all sizes that each source
keeps fractional up to the root; once they are paired too, some are turned over, long ones first, where that brings the source nearer to its
target. So a source misses its target by half the size of the shortest of these if the reserve is large enough, and by half of its longest row at most.

Rows alike in id, text and source are paired with each other first: of n such rows with fraction f, floor(n * f) get a copy more and
one goes on with what is left. So a group of any size enters the buckets as one row.

Sources are ordered by code point, null last; weights 1, 2, 3 repeat in that order. Null text: size 0, never taken. Rows with
null or repeated ids are rows of their own. The draws depend on the seed, the level, the source, and the ids and texts of a bucket
only, never on how the rows are dealt to files, tasks or cores: reruns agree. Which of several rows alike in id, text and source gets
the copy more is open where they differ in other columns. Without words every target is 0. Empty tables give empty results.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import checked, documents, keys_of, materialise, salted_join, short_batches

MOST = 3  # times its size that a source or a row is taken at most
BUCKET_ROWS, FAN, RESERVE, SEED = 512, 64, 256, 7
WORD = r"[^\x20\x09-\x0D]+"
#: Columns that tell groups of rows alike, and rows that one step of repeating makes of a group.
ALIKE, REPEAT = ["_id", "_text", "_source"], 4096


def targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: int = MOST) -> DataFrame:
    """source, source_size, target. One row per source in and out.

    With lam words a unit of weight, a source gets min(most * its size, weight * lam). Capped are the sources with the smallest
    most * size / weight; going up in that order, the first lam that caps no further source is the one all uncapped share.
    """
    order = W.orderBy(F.col("source").isNull(), F.encode("source", "UTF-8"))
    up = W.orderBy("ratio", F.col("source").isNull(), F.encode("source", "UTF-8"))
    total = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return (
        sizes.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
        .withColumn("cap", (F.col("source_size") * most).cast("double"))
        .withColumn("ratio", F.col("cap") / F.col("w"))
        .withColumn("below", F.coalesce(F.sum("cap").over(up.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("rest", F.sum("w").over(up.rowsBetween(0, W.unboundedFollowing)))
        .withColumn("lam", (F.sum("source_size").over(total) - F.col("below")) / F.col("rest"))
        .withColumn("at", F.row_number().over(up))
        .withColumn("lam", F.min(F.when(F.col("lam") <= F.col("ratio"), F.struct("at", "lam"))).over(total)["lam"])
        .select("source", "source_size", F.least("cap", F.col("w") * F.coalesce("lam", F.lit(0.0))).alias("target"))
    )


def pivot(size: np.ndarray, fraction: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, int]:
    """Pairs rows one after another; returns the fractions, 0 or 1 but for that of the row left over (its place, or -1)."""
    out, left = fraction.tolist(), -1
    draw = rng.random(len(out)).tolist()
    s = size.tolist()
    tiny = 1e-9
    for i in range(len(out)):
        if not tiny < out[i] < 1 - tiny:
            out[i] = float(round(out[i]))
            continue
        if left < 0:
            left = i
            continue
        a, b = out[left] * s[left], out[i] * s[i]  # words of the two
        up = min(s[left] - a, b)  # that may move to the first, or to the second
        down = min(a, s[i] - b)
        if draw[i] * (up + down) < down:
            a, b = a + up, b - up
        else:
            a, b = a - down, b + down
        pa, pb = a / s[left], b / s[i]
        first_whole = not tiny < pa < 1 - tiny
        second_whole = not tiny < pb < 1 - tiny
        out[left] = float(round(pa)) if first_whole else pa
        out[i] = float(round(pb)) if second_whole else pb
        left = i if first_whole and not second_whole else -1 if first_whole else left
    return np.array(out), left


def settle(part: pd.DataFrame, rng: np.random.Generator, new: int, last: bool) -> pd.DataFrame:
    """One source's rows of one bucket, long ones first: `fraction` made whole but for rows left `open` (reserve and residual).

    `new` rows, from the longest to the shortest, join the reserve."""
    f, size = part["fraction"].to_numpy(np.float64).copy(), part["size"].to_numpy(np.float64)
    broken = np.flatnonzero((f > 1e-9) & (f < 1 - 1e-9))
    held = part["reserve"].to_numpy(bool).copy()
    if new and len(broken):
        held[broken[np.linspace(0, len(broken) - 1, min(new, len(broken))).astype(int)]] = True
    kept = np.flatnonzero(held)
    if len(kept) > RESERVE:
        held[kept] = False
        held[kept[np.linspace(0, len(kept) - 1, RESERVE).astype(int)]] = True
    own, reserve = np.flatnonzero(~held), np.flatnonzero(held)
    f[own], left = pivot(size[own], f[own], rng)
    still = held.copy()
    if last:
        still[:] = False
        rows = np.sort(np.r_[own[left : left + 1] if left >= 0 else own[:0], reserve].astype(int))
        f[rows], left = pivot(size[rows], f[rows], rng)
        miss = 0.0
        if left >= 0:
            i = rows[left]
            miss, f[i] = (f[i] - round(f[i])) * size[i], round(f[i])
        for i in rows:  # long ones first: a row is turned over where that brings the source nearer to its target
            turned = miss + (2 * f[i] - 1) * size[i]
            if abs(turned) < abs(miss):
                miss, f[i] = turned, 1 - f[i]
    elif left >= 0:
        still[own[left]] = True
    return part.assign(fraction=f, reserve=held, open=still)


def copies(rows: DataFrame, seed: int = SEED, bucket_rows: int = BUCKET_ROWS, fan: int = FAN) -> DataFrame:
    """rows: ALIKE (unique), source, size, fraction, and others. Returns them with `fraction` rounded to 0 or 1."""
    n = rows.count()
    n_buckets = max(1, math.ceil(n / bucket_rows))
    order = ["size", "_key", *ALIKE]
    names = [*rows.columns, "_key", "reserve", "bucket", "level", "open"]
    keyed = rows.withColumn("_key", F.xxhash64(*ALIKE))
    current = keyed.withColumn("reserve", F.lit(False)).withColumn("bucket", F.pmod(F.xxhash64(F.lit(seed), *ALIKE), F.lit(n_buckets)))
    schema = current.withColumns({"level": F.lit(0), "open": F.lit(False)}).schema

    def run_for(level: int, last: bool, reserve: int):
        def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
            parts = []
            for source, part in frame.groupby("_source", sort=True):
                part = part.sort_values(order, ascending=[False, *[True] * (len(order) - 1)], kind="stable")
                rng = np.random.default_rng([seed, level, int(key[-1]), zlib.crc32(source.encode("utf-8", "surrogatepass"))])
                parts.append(settle(part, rng, reserve, last).assign(level=level, bucket=int(key[-1]) // fan))
            return pd.concat(parts)[names]

        return run

    done, level = [], 0
    while True:
        last = n_buckets == 1
        # Above the leaves each source has a tree of its own, so a group never holds more than FAN residuals and reserves.
        keys = ["_source", "bucket"] if level else ["bucket"]
        reserve = 0 if level else min(RESERVE // 4, math.ceil(RESERVE / n_buckets))
        out = materialise(current.groupBy(*keys).applyInPandas(run_for(level, last, reserve), schema), f"mix-level{level}")
        done.append(out.where(~F.col("open")))
        if last:
            break
        current = out.where("open").drop("level", "open")
        n_buckets, level = math.ceil(n_buckets / fan), level + 1
    result = done[0]
    for x in done[1:]:
        result = result.unionAll(x)
    return result.select(*rows.columns)


def alike(id_col: str, text_col: str, source_col: str) -> list[Column]:
    """What rows that count as one group share."""
    source = F.col(source_col).cast("string")
    return [*keys_of(id_col, text_col), F.when(source.isNull(), "n").otherwise(F.concat(F.lit("s"), source)).alias("_source")]


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """(groups: ALIKE, doc_id, source, size, n rows alike, whole copies of each of them, extra of them that get one more; sources:
    source, source_size, target)."""
    short_batches(docs.sparkSession)
    size = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("bigint")
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), size.alias("size"), *alike(id_col, text_col, source_col))
    # Partial counts before the exchange: a group of copies moves as one row a task.
    groups = rows.groupBy(*ALIKE).agg(F.min("doc_id").alias("doc_id"), F.min("source").alias("source"), F.min("size").alias("size"), F.count(F.lit(1)).alias("n"))
    groups = materialise(groups, "mix-sizes")
    sources = materialise(targets(groups.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))), "mix-sources")
    rate = sources.select(F.col("source").alias("_s"), F.when(F.col("source_size") > 0, F.least(F.lit(float(MOST)), F.col("target") / F.col("source_size"))).otherwise(0.0).alias("rate"))
    told = groups.join(checked(rate, sources.count(), 64), F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    told = told.withColumn("rate", F.when(F.col("size") > 0, F.col("rate")).otherwise(0.0)).withColumn("whole", F.floor(F.col("rate") + 1e-9))
    told = told.withColumn("over", F.greatest(F.col("rate") - F.col("whole"), F.lit(0.0)) * F.col("n")).withColumn("extra", F.floor(F.col("over") + 1e-9))
    told = told.withColumn("fraction", F.greatest(F.col("over") - F.col("extra"), F.lit(0.0))).drop("rate", "over")
    out = copies(told, seed)
    return out.withColumn("extra", F.col("extra") + F.round("fraction").cast("bigint")).drop("fraction"), sources


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies: one row per row."""
    groups, sources = mixed(docs)
    told = groups.join(checked(sources.withColumnRenamed("source", "_s"), sources.count(), 64), F.col("source").eqNullSafe(F.col("_s")))
    # The rows of a group are made from their number, in steps, so that no array holds a large group.
    step = F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("n") - 1) / REPEAT))).alias("_step")
    stepped = told.select("doc_id", "size", "source_size", "target", "n", "whole", "extra", step)
    place = F.explode(F.sequence(F.col("_step") * REPEAT, F.least("n", (F.col("_step") + 1) * REPEAT) - 1)).alias("_place")
    rows = stepped.select("doc_id", "size", "source_size", "target", "whole", "extra", place)
    n_copies = F.col("whole") + (F.col("_place") < F.col("extra")).cast("bigint")
    return rows.select("doc_id", "size", "source_size", "target", (F.col("size") * n_copies).alias("taken"), n_copies.alias("copies"))


def places(rows: DataFrame) -> DataFrame:
    """Adds `_place`, 0 to n-1 among the rows of a group; counted by file part, so that no group is sorted whole."""
    rows = materialise(rows.withColumn("_row", F.monotonically_increasing_id()), "mix-repeated").withColumn("_part", F.shiftright("_row", 33))
    counts = rows.groupBy(*ALIKE, "_part").agg(F.count(F.lit(1)).alias("_n"))
    before = F.coalesce(F.sum("_n").over(W.partitionBy(*ALIKE).orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    own = F.row_number().over(W.partitionBy(*ALIKE, "_part").orderBy("_row")) - 1
    return rows.withColumn("_own", own).join(counts.select(*ALIKE, "_part", before.alias("_before")), [*ALIKE, "_part"]).withColumn("_place", F.col("_before") + F.col("_own"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = SEED) -> DataFrame:
    """Rows of docs, all columns, each as often as the mix takes it."""
    groups, _ = mixed(docs, id_col, text_col, source_col, seed)
    groups = materialise(groups.select(*ALIKE, "n", "whole", "extra"), "mix-taken")
    packed = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), *alike(id_col, text_col, source_col))
    several, odd = groups.where("n > 1"), groups.where("n = 1 and whole + extra <> 1")
    n_several, n_odd = several.count(), odd.count()
    single = packed.join(checked(several.select(*ALIKE), n_several, 72), ALIKE, "left_anti")
    single = single.join(checked(odd.select(*ALIKE, (F.col("whole") + F.col("extra")).alias("_copies")), n_odd, 80), ALIKE, "left").select("row", F.coalesce("_copies", F.lit(1)).alias("_copies"))
    repeated = places(salted_join(packed, several, ALIKE, "n", n_several, 96)).select("row", (F.col("whole") + (F.col("_place") < F.col("extra")).cast("bigint")).alias("_copies"))
    taken = single.unionAll(repeated).where("_copies > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int"))).alias("_copy")).select("row.*")


def op7_mix_pivotal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(documents(spark, sf_dir))
