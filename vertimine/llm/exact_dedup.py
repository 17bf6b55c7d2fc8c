"""Exact duplicates by an extendible-hash index on shared files.

The key of a text is the 64-bit hash of its normalised form (listed characters deleted). The index has a directory of
2**depth slots; a slot names the bucket of the keys with its leading bits. Overfull buckets are split, and the
directory doubled where a bucket already is as deep as the directory, until no bucket holds more than CAPACITY keys or
the keys have no more bits.

Build: keys are counted by their leading bits, the directory grows from these counts, and each key with its number of rows goes to its
bucket's file. Use: keys of a single row are looked up in the index and done. The texts of all other rows go to
the owner task of their bucket, one entry for all rows of a task that have the same text. An owner holds a range of keys; it walks the entries key by
key, keeps a chain of the key's distinct texts, and compares each entry byte by byte with the chain. Entries with equal bytes are one group; texts that only
share a key end in different links of the chain. Owners answer by entry number, which never has more rows than one task read,
so a text that a third of all rows share is no hot key anywhere.

Null texts count as empty. Ids may be null or repeat: each row is a row of its own; of the longest original texts the row with
the smallest id stays (a null id after all others), of rows alike in that too one of them. Empty tables give empty results.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import checked, documents, materialise, short_batches, slices, small_enough

#: Deleted before texts are compared.
BLANK = " \t\n\x0b\x0c\r"
#: Keys a bucket holds at most; leading bits of a key that the directory may use.
CAPACITY, MOST_BITS = 1 << 13, 24
#: Bytes of distinct texts that a task gathers before it sends them on as entries.
ENTRY_BYTES = 16 << 20


def normalised(text: Column, delete: str = BLANK) -> Column:
    return F.translate(F.coalesce(text, F.lit("")), delete, "")


def key_of(norm: Column, key_bits: int = 64) -> Column:
    h = F.xxhash64(norm)
    return h if key_bits == 64 else F.shiftleft(h, 64 - key_bits)


@dataclass
class Directory:
    """Slots of an extendible hash: slot -> bucket number, ascending; depth of each bucket. Keys are looked up by their leading bits."""

    depth: int
    slots: np.ndarray
    depths: list[int]

    @classmethod
    def grown(cls, counts: dict[int, int], fine: int, capacity: int) -> Directory:
        """counts: keys by their `fine` leading bits. Splits from one bucket on until none is overfull."""
        have = np.zeros(1 << fine, np.int64)
        have[list(counts)] = list(counts.values())
        total = np.concatenate([[0], np.cumsum(have)])
        depth, todo, done = 0, [(0, 0)], []  # (leading bits, their number)
        while todo:
            bits, d = todo.pop()
            lo, hi = bits << (fine - d), (bits + 1) << (fine - d)
            if total[hi] - total[lo] > capacity and d < fine:
                depth = max(depth, d + 1)  # the directory doubles when the deepest bucket splits
                todo += [(bits * 2 + 1, d + 1), (bits * 2, d + 1)]
            else:
                done.append((bits, d))
        slots = np.zeros(1 << depth, np.int32)
        for i, (bits, d) in enumerate(done):  # the stack gives them in ascending order
            slots[bits << (depth - d) : (bits + 1) << (depth - d)] = i
        return cls(depth, slots, [d for _, d in done])

    def bucket(self, keys: np.ndarray) -> np.ndarray:
        return self.slots[keys.view(np.uint64) >> np.uint64(64 - self.depth)] if self.depth else np.zeros(len(keys), np.int32)


class ExtendibleIndex:
    """Keys and their row counts, by bucket, on shared files; the directory is what the driver and the tasks know of it."""

    def __init__(self, entries: DataFrame, directory: Directory, n_keys: int, n_owners: int):
        self.entries, self.directory, self.n_keys, self.n_owners = entries, directory, n_keys, n_owners

    @classmethod
    def build(cls, docs: DataFrame, text_col: str = "text", delete: str = BLANK, key_bits: int = 64, capacity: int = CAPACITY) -> ExtendibleIndex:
        spark = docs.sparkSession
        short_batches(spark)
        keys = docs.select(key_of(normalised(F.col(text_col), delete), key_bits).alias("key")).groupBy("key").agg(F.count(F.lit(1)).alias("n"))
        keys = materialise(keys, "dedup-keys")
        n_keys = keys.count()
        # Two bits more than an even spread needs: what they can't part stays in one bucket, larger than the others.
        fine = min(MOST_BITS, math.ceil(math.log2(max(1, n_keys / capacity))) + 2)
        counted = keys.groupBy(F.shiftrightunsigned("key", 64 - fine).alias("lead")).count().toArrow()  # n_keys / capacity * 8 rows at most
        directory = Directory.grown(dict(zip(counted["lead"].to_pylist(), counted["count"].to_pylist())), fine, capacity)
        # An owner holds neighbouring buckets; small indexes have as many owners as there are partitions to work on.
        n_owners = max(1, min(len(directory.depths), int(spark.conf.get("spark.sql.shuffle.partitions")) * 64))
        index = cls(keys, directory, n_keys, n_owners)
        index.entries = materialise(index.routed(keys).sortWithinPartitions("bucket", "key"), "dedup-index")
        return index

    def routed(self, rows: DataFrame) -> DataFrame:
        """rows (with `key`) and `bucket`, dealt by it: a task gets whole buckets."""
        sent = rows.sparkSession.sparkContext.broadcast(self.directory)
        at = rows.columns.index("key")
        schema = T.StructType([*rows.schema.fields, T.StructField("bucket", T.IntegerType())])

        def run(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sent.value.bucket(b.column(at).to_numpy(zero_copy_only=False)))], names=[*b.schema.names, "bucket"])

        return rows.mapInArrow(run, schema).repartition(self.n_owners, "bucket")

    def repeated(self) -> DataFrame:
        """Keys that several rows have, with the number of rows."""
        return self.entries.where(F.col("n") > 1).select("key", "n")


def gathered(rows: DataFrame) -> DataFrame:
    """rows: key, norm, id, len, carried. Out: `what` 0 for a row (entry number, id, length, carried), 1 for an entry (entry number, key, norm,
    rows, and the longest length with its smallest id). An entry is a text as often as a task has it between two flushes."""
    kind, fields = rows.schema["id"].dataType, rows.schema["carried"].dataType
    schema = T.StructType(
        [T.StructField(n, t) for n, t in (("what", T.IntegerType()), ("entry", T.LongType()), ("row", T.LongType()), ("id", kind), ("len", T.LongType()), ("carried", fields), ("key", T.LongType()), ("norm", T.StringType()), ("n", T.LongType()))]
    )

    def run(batches):
        task, n_rows, n_entries, known, size, types = TaskContext.get().partitionId() << 36, 0, 0, {}, 0, None

        def flush():
            # known: (key, norm) -> [entry, n, len, (id is null, id), row]
            texts, best = list(known), list(known.values())
            for at in range(0, len(best), 256):
                t, v = texts[at : at + 256], best[at : at + 256]
                m = len(v)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([1] * m, pa.int32()), pa.array([x[0] for x in v], pa.int64()), pa.array([x[4] for x in v], pa.int64()), pa.array([x[3][1] for x in v], types[0]), pa.array([x[2] for x in v], pa.int64()), pa.nulls(m, types[1]),
                     pa.array([x[0] for x in t], pa.int64()), pa.array([x[1] for x in t], pa.string()), pa.array([x[1] for x in v], pa.int64())],
                    names=schema.names,
                )

        for b in slices(batches, 500):
            types, entries, m = (b.column(2).type, b.column(4).type), [], b.num_rows
            for k, (key, norm, i, length) in enumerate(zip(*(b.column(c).to_pylist() for c in range(4)))):
                entry = known.get((key, norm))
                if entry is None:
                    known[key, norm] = entry = [task + n_entries, 0, -1, (True, None), -1]
                    n_entries, size = n_entries + 1, size + len(norm)
                entry[1] += 1
                if length > entry[2] or length == entry[2] and (entry[3][0] and i is not None or i is not None and i < entry[3][1]):
                    entry[2:] = [length, (i is None, i), task + n_rows + k]
                entries.append(entry[0])
            rows_ = pa.array(range(task + n_rows, task + n_rows + m), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([0] * m, pa.int32()), pa.array(entries, pa.int64()), rows_, b.column(2), b.column(3), b.column(4), pa.nulls(m, pa.int64()), pa.nulls(m, pa.string()), pa.nulls(m, pa.int64())], names=schema.names)
            n_rows += m
            if size > ENTRY_BYTES:
                yield from flush()
                known, size = {}, 0
        if known:
            yield from flush()

    return rows.select("key", "norm", "id", "len", "carried").mapInArrow(run, schema)


def chained(index: ExtendibleIndex, entries: DataFrame) -> DataFrame:
    """entry, link_of (the smallest entry with its bytes), len, id, row, n: every entry after its owner has walked the key's chain of texts."""
    kind = entries.schema["id"].dataType
    schema = T.StructType([T.StructField(n, t) for n, t in (("entry", T.LongType()), ("link_of", T.LongType()), ("len", T.LongType()), ("id", kind), ("row", T.LongType()), ("n", T.LongType()))])
    routed = index.routed(entries.select("key", "norm", "entry", "len", "id", "row", "n")).sortWithinPartitions("bucket", "key", "entry")

    def run(batches):
        key, chain = None, {}  # the texts of one key, each with its first entry; compared byte by byte
        for b in slices(batches, 500):
            first = []
            for k, norm, entry in zip(*(b.column(c).to_pylist() for c in range(3))):
                if k != key:
                    key, chain = k, {}
                first.append(chain.setdefault(norm, entry))
            yield pa.RecordBatch.from_arrays([b.column(2), pa.array(first, pa.int64()), b.column(3), b.column(4), b.column(5), b.column(6)], names=schema.names)

    return routed.drop("bucket").mapInArrow(run, schema)


def _classes(docs: DataFrame, text_col: str, id_col: str, delete: str, key_bits: int, capacity: int, carry: Column):
    """(rows with a key of their own: id, carried; the others: id, carried, keep_id, n, kept)."""
    index = ExtendibleIndex.build(docs, text_col, delete, key_bits, capacity)
    shared = materialise(index.repeated().select("key"), "dedup-shared")
    n_shared = shared.count()
    norm = normalised(F.col(text_col), delete)
    rows = docs.select(key_of(norm, key_bits).alias("key"), norm.alias("norm"), F.col(id_col).alias("id"), F.length(F.coalesce(F.col(text_col), F.lit(""))).cast("bigint").alias("len"), carry.alias("carried"))
    if small_enough(n_shared, 16):
        single, alike = rows.join(F.broadcast(shared), "key", "left_anti"), rows.join(F.broadcast(shared), "key", "left_semi")
    else:  # too many to send to all: the owners see every row's text, and a single row is a group of one
        single, alike = rows.limit(0), rows
    both = materialise(gathered(alike), "dedup-alike")
    linked = materialise(chained(index, both.where("what = 1")), "dedup-links")
    best = F.min(F.struct((-F.col("len")).alias("len"), F.col("id").isNull().alias("no_id"), F.col("id").alias("id"), F.col("row").alias("row")))
    groups = linked.groupBy("link_of").agg(best.alias("best"), F.sum("n").alias("n")).select("link_of", "n", F.col("best.id").alias("keep_id"), F.col("best.row").alias("keep_row"))
    n_entries = linked.count()
    # One row an entry on both sides but the rows; an entry's rows all come from one task.
    told = materialise(linked.select("entry", "link_of").join(checked(groups, n_entries, 48), "link_of").drop("link_of"), "dedup-groups")
    members = both.where("what = 0").select("entry", "row", "id", "carried").join(checked(told, n_entries, 48), "entry")
    return single.select("id", "carried"), members.select("id", "carried", "keep_id", "n", (F.col("row") == F.col("keep_row")).alias("kept"))


def classify(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", delete: str = BLANK, key_bits: int = 64, capacity: int = CAPACITY) -> DataFrame:
    """One row per row: doc_id, keep_id, group_size, kept, text_sha256 (of the normalised text)."""
    sha = F.sha2(F.encode(normalised(F.col(text_col), delete), "UTF-8"), 256)
    single, members = _classes(docs, text_col, id_col, delete, key_bits, capacity, sha)
    return single.select(F.col("id").alias("doc_id"), F.col("id").alias("keep_id"), F.lit(1).cast("bigint").alias("group_size"), F.lit(True).alias("kept"), F.col("carried").alias("text_sha256")).unionAll(
        members.select(F.col("id").alias("doc_id"), "keep_id", F.col("n").alias("group_size"), "kept", F.col("carried").alias("text_sha256"))
    )


def keep_first(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", delete: str = BLANK, key_bits: int = 64, capacity: int = CAPACITY) -> DataFrame:
    """The rows of docs that stay, with all their columns."""
    row = F.struct(*[docs[c] for c in docs.columns])
    single, members = _classes(docs, text_col, id_col, delete, key_bits, capacity, row)
    return single.select("carried.*").unionAll(members.where("kept").select("carried.*"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(documents(spark, sf_dir))


OP3_SQL = r"""
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS len,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents
), g AS (
  SELECT *, first_value(doc_id) OVER w AS keep_id, row_number() OVER w AS pos,
         count(*) OVER (PARTITION BY text_sha256) AS group_size
  FROM t WINDOW w AS (PARTITION BY text_sha256 ORDER BY len DESC, doc_id NULLS LAST)
)
SELECT doc_id, keep_id, group_size, pos = 1 AS kept, text_sha256 FROM g
"""
