"""Toxicity scores: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features of a text, each counted once: its words, the words' first four letters (so that an insult is known in all its
endings), its pairs of neighbouring words, its pairs of words one apart, all hashed into `bits` bits. FTRL-proximal keeps a step size per coordinate and an L1 term, so most weights stay exactly zero and the
model that goes to the workers is a few kB of non-zero weights, at most 2**bits of them.

Labels: rows whose label is null are left out; of several labels of one id the largest counts. The model is fitted on at most
`max_train` labelled rows, rows alike in id and text being one (half of each class at most, those with the smallest hash of their id
and text); the intercept is put right for the share of each class that was taken. Null and empty texts have no features and get the intercept's score. Repeated rows
score alike. Without any label of a class the score is the share of label 1 among the labels (0 without labels).
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import KEPT_CHARS, documents, materialise, release_memory, short_batches, slices, worker_table

WORD = re.compile(r"[^\W_]+")
MAX_WORDS = 200_000  # of a worker's table of word hashes, before it starts anew


def word_hashes(text: str) -> np.ndarray:
    """Per word a hash of it in the lower 32 bits, of its start in the upper ones."""
    words, known = WORD.findall(text.lower()), worker_table("toxicity")
    try:
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    except KeyError:
        if len(known) >= MAX_WORDS:
            known.clear()
        new = [w for w in set(words) if w not in known]
        found = {w: zlib.crc32(w.encode("utf-8", "surrogatepass")) | zlib.crc32(b"^" + w[:4].encode("utf-8", "surrogatepass")) << 32 for w in new}
        known.update((w, h) for w, h in found.items() if len(w) <= KEPT_CHARS)
    return np.fromiter([known[w] if w in known else found[w] for w in words], np.uint64, len(words))


def spread(x: np.ndarray, bits: int) -> np.ndarray:
    x = x * np.uint32(0x9E3779B1)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0x85EBCA77)
    return x >> np.uint32(32 - bits)


def features(h: np.ndarray, bits: int) -> np.ndarray:
    """Hashed words, word starts, word pairs and skip pairs of one text, with repeats."""
    start, h = (h >> np.uint64(32)).astype(np.uint32), h.astype(np.uint32)
    pair = h[:-1] * np.uint32(31) + h[1:] + np.uint32(0x51ED270B)
    skip = h[:-2] * np.uint32(127) + h[2:] * np.uint32(3) + np.uint32(0x2545F491)
    return spread(np.concatenate([h, start, pair, skip]), bits)


@dataclass
class FTRL:
    """Per-coordinate FTRL-proximal for log loss with 0/1 features."""

    bits: int = 20
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 6.0
    l2: float = 0.1
    epochs: int = 8

    def fit(self, rows: list[np.ndarray], labels: list[int]) -> tuple[np.ndarray, np.ndarray, float]:
        """Non-zero coordinates, their weights, and the intercept. rows: each text's distinct features, in a fixed order."""
        z, n = np.zeros(1 << self.bits), np.zeros(1 << self.bits)
        z0 = n0 = 0.0
        for _ in range(self.epochs):
            for x, y in zip(rows, labels, strict=True):
                zx, nx = z[x], n[x]
                root = np.sqrt(nx)
                w = np.where(np.abs(zx) <= self.l1, 0.0, -(zx - np.sign(zx) * self.l1) / ((self.beta + root) / self.alpha + self.l2))
                w0 = -z0 / ((self.beta + n0**0.5) / self.alpha)
                g = 1 / (1 + np.exp(-np.clip(w.sum() + w0, -35, 35))) - y
                more = nx + g * g
                z[x] = zx + g - (np.sqrt(more) - root) / self.alpha * w
                n[x] = more
                z0 += g - ((n0 + g * g) ** 0.5 - n0**0.5) / self.alpha * w0
                n0 += g * g
        at = np.flatnonzero(np.abs(z) > self.l1)
        w = -(z[at] - np.sign(z[at]) * self.l1) / ((self.beta + np.sqrt(n[at])) / self.alpha + self.l2)
        return at.astype(np.uint32), w.astype(np.float32), float(-z0 / ((self.beta + n0**0.5) / self.alpha))


@dataclass
class Model:
    bits: int
    at: np.ndarray
    weights: np.ndarray
    intercept: float

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << self.bits, np.float32)
        out[self.at] = self.weights
        return out

    def score(self, texts: list[str | None], dense: np.ndarray) -> np.ndarray:
        out = np.full(len(texts), self.intercept)
        for i, t in enumerate(texts):
            if t:
                x = features(word_hashes(t), self.bits)
                w = dense[x]
                hit = np.flatnonzero(w)
                if len(hit):
                    _, first = np.unique(x[hit], return_index=True)
                    out[i] += w[hit[first]].sum(dtype=np.float64)
        return 1 / (1 + np.exp(-np.clip(out, -35, 35)))


def held_out(id_col: str = "doc_id", fold: int = 0, folds: int = 5) -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(folds)) == fold, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", id_col: str = "doc_id", text_col: str = "text", max_train: int = 16_384, ftrl: FTRL | None = None) -> Model:
    """Fit on rows of docs that `labels` (id_col, label) marks. Reaches the driver: at most max_train rows of features."""
    ftrl = ftrl or FTRL()
    marked = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("_id")).agg(F.max(label).cast("int").alias("_label")).where("_label in (0, 1)")
    count = {r["_label"]: r["count"] for r in marked.groupBy("_label").count().collect()}
    if len(count) < 2:
        share = float(next(iter(count), 0))
        return Model(ftrl.bits, np.zeros(0, np.uint32), np.zeros(0, np.float32), 35.0 if share else -35.0)

    def first(rows: DataFrame, have: dict[int, int], order: list) -> tuple[DataFrame, dict[int, int]]:
        """At most max_train of rows, half of each class unless the other has fewer."""
        share = {k: min(n, max_train // 2) for k, n in have.items()}
        for k in (0, 1):
            share[k] = min(have.get(k, 0), max_train - share.get(1 - k, 0))
        parts = [rows.where(F.col("_label") == k).orderBy(*order).limit(share[k]) for k in (0, 1)]
        return parts[0].unionAll(parts[1]), share

    # Ids first, which bounds the broadcast; then the distinct texts of these ids, which bounds the rows: an id may repeat.
    ids, _ = first(marked, count, [F.xxhash64("_id"), F.col("_id")])
    own = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_text")).withColumn("_hash", F.xxhash64("_text"))
    pairs = materialise(own.join(F.broadcast(ids), "_id").select("_id", "_hash", "_label").distinct(), "toxic-ids")
    have = {r["_label"]: r["count"] for r in pairs.groupBy("_label").count().collect()}
    some, taken = first(pairs, have, [F.xxhash64("_id"), F.col("_id"), F.col("_hash")])
    sample = own.join(F.broadcast(some), ["_id", "_hash"])
    bits = ftrl.bits
    short_batches(docs.sparkSession)

    def run(batches):
        for b in slices(batches, 500):
            rows = [np.unique(features(word_hashes(t), bits)).tobytes() for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.binary()), *b.columns[1:]], names=["x", "y", "h", "t"])

    got = sample.select("_text", "_label", F.xxhash64("_id").alias("h"), "_hash").mapInArrow(run, "x binary, y int, h bigint, t bigint").dropDuplicates(["h", "t"]).toArrow()
    rows = sorted(zip(got["h"].to_pylist(), got["x"].to_pylist(), got["y"].to_pylist(), strict=True))
    del got
    at, w, intercept = ftrl.fit([np.frombuffer(x, np.uint32) for _, x, _ in rows], [y for *_, y in rows])
    del rows
    release_memory()
    shift = np.log(count[1] / count[0]) - np.log(taken[1] / taken[0]) if taken[0] and taken[1] else 0.0
    return Model(bits, at, w, intercept + float(shift))


def with_scores(docs: DataFrame, model: Model, text_col: str, keep: list[Column], schema: str, below: float | None = None) -> DataFrame:
    """`keep` columns and the score; with `below`, only rows that score less (then `keep` goes out without the score)."""
    short_batches(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = sent.value
        dense = m.dense()
        for b in slices(batches):
            score = m.score(b.column(0).to_pylist(), dense)
            if below is None:
                yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(score)], names=[*b.schema.names[1:], "score"])
            else:
                yield pa.RecordBatch.from_arrays(b.columns[1:], names=b.schema.names[1:]).filter(pa.array(score < below))

    return docs.select(F.col(text_col).alias("_text"), *keep).mapInArrow(run, schema)


def keep_clean(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """Rows of docs, all columns, that score below the threshold."""
    named = [docs[c].alias(f"_{i}") for i, c in enumerate(docs.columns)]
    types = ", ".join(f"_{i} {f.dataType.simpleString()}" for i, f in enumerate(docs.schema))
    return with_scores(docs, model, text_col, named, types, threshold).toDF(*docs.columns)


def op6_toxicity_ftrl(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = train(docs, labels.where(~held_out()))
    kind = docs.schema["doc_id"].dataType.simpleString()
    out = with_scores(docs, model, "text", [F.col("doc_id"), held_out().alias("held_out")], f"doc_id {kind}, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
