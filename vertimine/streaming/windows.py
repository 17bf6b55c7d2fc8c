"""Baskets, counts and mining over event streams.

Every operator takes a streaming (or batch) frame with ts, user_id and event_type. run_available() drains a source once into
a Parquet table, which is how the queries show that a stream's result equals the batch result.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LATE = "1 hour"


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    path = f"{sf_dir}/events.parquet"
    events = spark.readStream.schema(spark.read.parquet(path).schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return events.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need instants


def shared(spark: SparkSession, name: str) -> str:
    top = spark.conf.get("spark.checkpoint.dir", None) or "file:///tmp/checkpoints"
    return f"{top.rstrip('/')}/vertimine-stream/{name}-{uuid.uuid4().hex}"


def run_available(stream: DataFrame, name: str, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Read what is there, write it, return the written table."""
    spark, path = stream.sparkSession, shared(stream.sparkSession, name)
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/state")
    if each is not None or mode != "append":
        if each is None:

            def each(batch: DataFrame, number: int) -> None:
                batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/data/batch={number}")

        writer.foreachBatch(each).start().awaitTermination()
    else:
        writer.format("parquet").option("path", f"{path}/data").start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/data")


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    """One basket per user and window: (user_id, start, items)."""
    at = events.withWatermark("ts", LATE).groupBy("user_id", F.window("ts", width))
    return at.agg(F.array_sort(F.collect_set("event_type")).alias("items")).select("user_id", F.col("window.start").cast("timestamp_ntz").alias("start"), F.array_join("items", "|").alias("items"))


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    at = events.withWatermark("ts", LATE).groupBy("event_type", F.window("ts", width, step))
    return at.agg(F.count(F.lit(1)).alias("n")).select("event_type", F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


def session(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    at = events.withWatermark("ts", LATE).groupBy("user_id", F.session_window("ts", gap))
    return at.agg(F.count(F.lit(1)).alias("n"), F.array_join(F.array_sort(F.collect_set("event_type")), "|").alias("items")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n", "items")


def deduplicated(events: DataFrame) -> DataFrame:
    """First event of each user, type and hour."""
    hour = events.withColumn("hour", F.date_trunc("hour", "ts")).withWatermark("hour", LATE)
    return hour.dropDuplicates(["user_id", "event_type", "hour"]).select("user_id", "event_type", F.col("hour").cast("timestamp_ntz").alias("hour"))


def pair_counts(events: DataFrame, width: str = "1 day") -> DataFrame:
    """How many users had both types in a window, from windowed baskets: (start, i, j, users)."""
    baskets = tumbling(events, width).select("start", F.split("items", r"\|").alias("items"))
    at = baskets.select("start", "items", F.posexplode("items").alias("pos", "i"))
    return at.select("start", "i", F.explode(F.slice("items", F.col("pos") + 2, F.size("items"))).alias("j"))


def mine_windows(min_count: int, path: str) -> Callable[[DataFrame, int], None]:
    """foreachBatch body: mines each batch's closed windows; a repeated batch overwrites its own output."""
    from vertimine.operators.bottomup import as_text
    from vertimine.plans.mine import mine
    from vertimine.sources.baskets import Transactions

    def each(batch: DataFrame, number: int) -> None:
        frame = batch.persist()
        if not frame.isEmpty():
            rows = frame.select(F.xxhash64("user_id", "start").alias("tid"), F.explode(F.split("items", r"\|")).alias("item"))
            as_text(mine(Transactions.of(rows), "filtered_mod", min_count=min_count)).write.mode("overwrite").parquet(f"{path}/batch={number}")
        frame.unpersist()

    return each


def decayed_counts(events: DataFrame, half_life_days: float = 7.0) -> DataFrame:
    """Per user and type a count that halves every half_life_days, as of the user's last event of the type: state kept per user.

    An event that comes late weighs what it would weigh now, and the clock stays. `as_of` orders the updates of a user and type."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key: tuple, frames, state):
        kinds, weights, days = state.get if state.exists else ([], [], [])
        known = {k: (w, d) for k, w, d in zip(kinds, weights, days)}
        rows = pd.concat(list(frames)).sort_values("ts")
        since = (rows["ts"] - pd.Timestamp("1970-01-01")).dt.total_seconds() / 86_400
        for day, kind in zip(since, rows["event_type"]):
            weight, at = known.get(kind, (0.0, day))
            now = max(at, day)
            known[kind] = (weight * 0.5 ** ((now - at) / half_life_days) + 0.5 ** ((now - day) / half_life_days), now)
        state.update((list(known), [w for w, _ in known.values()], [d for _, d in known.values()]))
        yield pd.DataFrame({"user_id": [key[0]] * len(known), "event_type": list(known), "weight": [w for w, _ in known.values()], "as_of": [d for _, d in known.values()]})

    return events.groupBy("user_id").applyInPandasWithState(
        update, "user_id bigint, event_type string, weight double, as_of double", "kinds array<string>, weights array<double>, days array<double>", "update", GroupStateTimeout.NoTimeout
    )
