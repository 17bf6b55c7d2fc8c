"""License texts in documents by diagonal voting.

All rolling word k-gram hashes of a text are compared with those of the templates; a hit of text position x and template
position t votes for the diagonal x - t. Votes are summed by diagonal, neighbouring diagonals (a few words put in or
left out) are merged to spans, and spans are verified: a short phrase must stand whole and unchanged on one diagonal, a longer
template must be covered to at least MIN_COVER. Grams are compared by hash and then by their words, so that a hash
collision is no hit. Words are runs of digits, a-z and characters beyond ASCII after lower-casing A-Z.

Null texts have no words. Each row has a row id of its own, so null and repeated ids do no harm. Empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import ascii_lower, checked, documents, materialise

#: What parts words.
APART = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Phrases that must stand word for word, and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Beginnings of public license texts, found also with small changes.
TEXTS = {
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files": "mit",
    "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license": "apache-2.0",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license": "gpl",
    "this work is licensed under a creative commons attribution share alike international license": "cc-by-sa",
    "this source code form is subject to the terms of the mozilla public license": "mpl-2.0",
    "this is free and unencumbered software released into the public domain": "unlicense",
    "no part of this publication may be reproduced stored in a retrieval system or transmitted in any form": "reserved",
}
SHORT_K, LONG_K, MIN_COVER, SHIFT = 2, 4, 0.6, 3


def words_of(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(text), APART), lambda w: w != "")


def templates(spark: SparkSession, phrases: dict[str, str], texts: dict[str, str]) -> tuple[DataFrame, dict[int, int], int]:
    """(template, label, exact, words, grams, k, at, gram, h) with one row a template position; rows by k; bytes of it all."""
    rows = []
    for n, (text, label, exact) in enumerate([(t, x, True) for t, x in phrases.items()] + [(t, x, False) for t, x in texts.items()]):
        words = text.split()
        k = min(SHORT_K if exact else LONG_K, len(words))
        rows += [(n, label, exact, len(words), len(words) - k + 1, k, at, words[at : at + k]) for at in range(len(words) - k + 1)]
    table = spark.createDataFrame(rows, "template int, label string, exact boolean, words int, grams int, k int, at int, gram array<string>")
    table = table.withColumn("h", F.when(F.lit(False), F.lit(0).cast("bigint")))
    sizes = {k: sum(r[5] == k for r in rows) for k in sorted({r[5] for r in rows})}
    for k in sizes:
        table = table.withColumn("h", F.when(F.col("k") == k, F.xxhash64(F.lit(k), *[F.get("gram", F.lit(j)) for j in range(k)])).otherwise(F.col("h")))
    return table, sizes, sum(64 + sum(map(len, r[7])) for r in rows)


def scan(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", phrases: dict[str, str] | None = None, texts: dict[str, str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(rows: _row, doc_id, n_words; spans: _row, template, label, exact, first, last (words from 0), cover)."""
    spark = docs.sparkSession
    table, sizes, n_bytes = templates(spark, PHRASES if phrases is None else phrases, TEXTS if texts is None else texts)
    split = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("doc_id"), words_of(F.col(text_col)).alias("words"))
    # Every position with its grams' hashes, joined to the template positions with that hash; a row without any hit stays as one row.
    found = split.select("_row", "doc_id", F.size("words").cast("bigint").alias("n_words"), F.posexplode_outer(windows(max(sizes, default=1))).alias("pos", "w"))
    hashes = [F.struct(F.lit(k).alias("k"), F.when(F.col(f"w.w{k - 1}").isNotNull(), F.xxhash64(F.lit(k), *[F.col(f"w.w{j}") for j in range(k)])).alias("h")) for k in sizes]
    hashes = hashes or [F.struct(F.lit(0).alias("k"), F.lit(None).cast("bigint").alias("h"))]
    positions = found.select("_row", "doc_id", "n_words", "pos", "w", F.explode(F.array(*hashes)).alias("g")).select("_row", "doc_id", "n_words", "pos", "w", F.col("g.k").alias("k"), F.col("g.h").alias("h"))
    sides = table.drop("k").withColumnsRenamed({"words": "n_template"}).withColumn("_k", F.size("gram"))
    met = positions.join(checked(sides, 1, n_bytes), "h", "left")
    same = F.col("template").isNotNull() & (F.concat_ws(" ", *[F.when(F.col("_k") > j, F.col(f"w.w{j}")) for j in range(max(sizes, default=1))]) == F.array_join("gram", " "))
    first = (F.coalesce("pos", F.lit(0)) == 0) & (F.col("k") == min(sizes, default=0))  # carries the row itself
    kept = met.select("_row", "doc_id", "n_words", first.alias("whole"), same.alias("hit"), "template", "label", "exact", "n_template", "grams", F.col("_k").alias("k"), "pos", "at").where("whole or hit")
    kept = materialise(kept, "license-hits")
    rows = kept.where("whole").select("_row", "doc_id", "n_words").distinct()
    hits = kept.where("hit")
    votes = hits.groupBy("_row", "template", "label", "exact", "n_template", "grams", "k", (F.col("pos") - F.col("at")).alias("diagonal")).agg(F.count(F.lit(1)).alias("votes"), F.min("pos").alias("first"), F.max("pos").alias("last"), F.collect_set("at").alias("ats"))
    whole = votes.where(F.col("exact") & (F.col("votes") == F.col("grams"))).select("_row", "template", "label", "exact", F.col("diagonal").cast("bigint").alias("first"), (F.col("last") + F.col("k") - 1).cast("bigint").alias("last"), F.lit(1.0).alias("cover"))
    near = W.partitionBy("_row", "template").orderBy("diagonal")
    merged = (
        votes.where(~F.col("exact"))
        .withColumn("new", (F.coalesce(F.col("diagonal") - F.lag("diagonal").over(near), F.lit(SHIFT + 1)) > SHIFT).cast("int"))
        .withColumn("span", F.sum("new").over(near))
        .groupBy("_row", "template", "label", "exact", "n_template", "k", "span")
        .agg(F.collect_set("ats").alias("ats"), F.min("first").alias("first"), F.max("last").alias("last"))
        .withColumn("covered", F.size(F.array_distinct(F.flatten(F.transform(F.flatten("ats"), lambda t: F.sequence(t, t + F.col("k") - 1))))))
        .withColumn("cover", F.col("covered") / F.col("n_template"))
        .where(F.col("cover") >= MIN_COVER)
        .select("_row", "template", "label", "exact", F.col("first").cast("bigint").alias("first"), (F.col("last") + F.col("k") - 1).cast("bigint").alias("last"), "cover")
    )
    return rows, whole.unionByName(merged)


def windows(k: int) -> Column:
    """Array of (w0 ... wk-1): each word of column `words` with the k - 1 after it, null beyond the end."""
    words = F.col("words")
    shifted = [words if j == 0 else F.slice(words, F.lit(j + 1), F.greatest(F.size(words) - j, F.lit(0))) for j in range(k)]
    return F.arrays_zip(*[x.alias(f"w{j}") for j, x in enumerate(shifted)])


def op2_license_diagonals(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, spans = scan(documents(spark, sf_dir))

    def labels(where: Column | None) -> Column:
        return F.array_join(F.array_sort(F.collect_set(F.col("label") if where is None else F.when(where, F.col("label")))), ",")

    base = F.col("exact")
    told = spans.groupBy("_row").agg(
        F.count(F.when(base, 1)).alias("n_base"), F.min(F.when(base, F.col("first"))).alias("first_word"), F.max(F.when(base, F.col("first"))).alias("last_word"),
        labels(base).alias("base_labels"), labels(None).alias("labels"), F.max("cover").alias("score"),
    )
    full = rows.join(told, "_row", "left").drop("_row")
    return full.fillna({"n_base": 0, "base_labels": "", "labels": "", "score": 0.0})
