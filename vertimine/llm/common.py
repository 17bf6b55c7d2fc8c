"""What the training-data operators share: the folder all machines see, tables written there, joins that stand skew."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import uuid
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertimine.session import ship

#: Used only where the session names no spark.checkpoint.dir, as in tests on one machine.
LOCAL_SHARED_DIR = "file:///tmp/checkpoints"
#: A side is broadcast only if its measured rows times its row width stay below this.
BROADCAST_BYTES = 32 << 20
#: Rows of one hot key that one salted part holds.
SALT_ROWS = 2048

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's spark.checkpoint.dir. Our own only where that is unset and all is one process."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.conf.get("spark.master", "").split("[")[0] == "local":
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return (named or LOCAL_SHARED_DIR).rstrip("/")


def materialise(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: cuts lineage and outlives lost executors.

    Generated row ids and random draws are frozen by it. The tables are removed when the driver's process ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/vertimine/{name}-{uuid.uuid4().hex}"
    df.write.mode("overwrite").option("compression", codec).parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def drop_tables(under: str | None = None) -> None:
    """Remove written tables (all, or those whose name starts with `under`), best effort."""
    for item in list(_written):
        spark, path = item
        if under is None or path.rsplit("/", 1)[-1].startswith(under):
            try:
                where = spark._jvm.org.apache.hadoop.fs.Path(path)
                where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(where, True)
            except Exception:  # noqa: BLE001  the session may have ended
                pass
            _written.remove(item)


atexit.register(drop_tables)


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only; null becomes empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def small_enough(n_rows: int, row_bytes: int) -> bool:
    return n_rows * row_bytes <= BROADCAST_BYTES


def checked(df: DataFrame, n_rows: int, row_bytes: int) -> DataFrame:
    """Hint a broadcast if the measured size allows; else leave the join to shuffle."""
    return F.broadcast(df) if small_enough(n_rows, row_bytes) else df


def salted_join(rows: DataFrame, groups: DataFrame, on: list[str], size: str, n_groups: int, row_bytes: int = 64) -> DataFrame:
    """Join many rows to one row per group where one group may own a third of all rows.

    `groups` is unique on `on` and has the group's row count in column `size`. Small group tables are broadcast after the
    size check; otherwise each group is repeated once per SALT_ROWS of its rows and the rows are dealt over the repeats.
    """
    if small_enough(n_groups, row_bytes):
        return rows.join(F.broadcast(groups), on)
    parts = F.ceil(F.col(size) / F.lit(SALT_ROWS)).cast("int")
    spread = groups.withColumn("_part", F.explode(F.sequence(F.lit(0), F.greatest(parts, F.lit(1)) - 1)))
    counts = groups.select(*on, F.greatest(parts, F.lit(1)).alias("_parts")).where(F.col("_parts") > 1)
    few = counts.count()  # only groups above SALT_ROWS rows: at most all rows / SALT_ROWS
    dealt = (
        rows.join(checked(counts, few, 32), on, "left")
        .withColumn("_part", F.pmod(F.monotonically_increasing_id(), F.coalesce("_parts", F.lit(1)).cast("long")).cast("int"))
        .drop("_parts")
    )
    return dealt.join(spread, [*on, "_part"]).drop("_part")


def keys_of(id_col: str = "doc_id", text_col: str = "text") -> list[Column]:
    """A row's identity for semi joins: its id (may be null) and a hash of its text; equal rows share it."""
    return [F.coalesce(F.col(id_col).cast("string"), F.lit("\x00")).alias("_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit("\x00"))).alias("_text")]


def without(docs: DataFrame, gone: DataFrame, n_gone: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of docs whose identity is not in `gone` (columns _id, _text); all columns kept, clashing names untouched."""
    i, t = keys_of(id_col, text_col)
    packed = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), i, t)
    return packed.join(checked(gone, n_gone, 48), ["_id", "_text"], "left_anti").select("row.*")


#: Rows of an Arrow batch: texts can be long, and a batch stands in memory twice, in the JVM and in Python.
BATCH_ROWS, BATCH_BYTES = 1000, 32 << 20
#: Characters of the longest word or piece that a worker's table keeps, so that bounds in entries bound the bytes too.
KEPT_CHARS = 64


def short_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batch size to BATCH_ROWS and BATCH_BYTES (settings that may change at any time); never raises it.

    Also gives this package to the executors' Python, so that stages work when they are called one by one."""
    ship(spark)
    for name, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        with contextlib.suppress(Exception):  # a Spark that has no such setting
            if not 0 < int(spark.conf.get(name, str(1 << 31))) <= most:
                spark.conf.set(name, str(most))


#: Tables that a Python worker keeps between tasks, by operator. Only the operator at work has any.
_tables: dict[str, dict] = {}


def release_memory() -> None:
    """Give freed memory back to the system where the C library can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def worker_table(operator: str) -> dict:
    if operator not in _tables:
        if _tables:
            _tables.clear()
            release_memory()
        _tables[operator] = {}
    return _tables[operator]


#: Bytes of text that a slice of a batch holds, but for a single longer text.
SLICE_BYTES = 4 << 20


def text_ends(column: pa.Array) -> np.ndarray | None:
    """For strings and bytes the place of each value's start and of the last one's end; None for other types."""
    kind = column.type
    if pa.types.is_string(kind) or pa.types.is_binary(kind):
        return np.frombuffer(column.buffers()[1], np.int32, len(column) + 1, column.offset * 4).astype(np.int64)
    if pa.types.is_large_string(kind) or pa.types.is_large_binary(kind):
        return np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    return None


def slices(batches: Iterable, rows: int = 1000, most_bytes: int = SLICE_BYTES):
    """Arrow batches cut into small ones, by rows and by the bytes of their texts; Arrow's spare memory goes back at the end."""
    for b in batches:
        ends = sum((x for x in map(text_ends, b.columns) if x is not None), np.zeros(b.num_rows + 1, np.int64)) if b.num_rows else None
        at = 0
        while at < b.num_rows:
            to = min(b.num_rows, at + rows, max(at + 1, int(np.searchsorted(ends, ends[at] + most_bytes, "right")) - 1))
            yield b.slice(at, to - at)
            at = to
    pa.default_memory_pool().release_unused()
