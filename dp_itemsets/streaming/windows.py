"""Windowed transactions and incremental bins over an event stream.

A transaction is what a user emits in a window.  With tumbling or session
windows each event lies in one transaction; a sliding window puts it into
several, which multiplies what one event can change, and ``unit`` says so.
Noise is drawn once a window is final: append mode emits each just once.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.noise import NoiseSource
from ..operators.bases import BasisSet

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, name: str = "events.parquet") -> DataFrame:
    """The events of a folder as a stream; ts becomes a UTC timestamp, which watermarks need."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", name).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def event_batch(spark: SparkSession, folder: str, name: str = "events.parquet") -> DataFrame:
    return spark.read.schema(EVENTS).parquet(f"{folder}/{name}").withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(length: str) -> Column:
    return F.window("ts", length)


def sliding(length: str, step: str) -> Column:
    return F.window("ts", length, step)


def sessions(gap: str) -> Column:
    return F.session_window("ts", gap)


def transactions(events: DataFrame, window: Column, delay: str | None = "1 day", item: str = "event_type") -> DataFrame:
    """(user_id, opened, closed, items): one row per user and window; with a delay, rows later than that are dropped."""
    timely = events.withWatermark("ts", delay) if delay else events
    grouped = timely.groupBy("user_id", window.alias("w")).agg(F.sort_array(F.collect_set(item)).alias("items"))
    return grouped.select("user_id", F.col("w.start").alias("opened"), F.col("w.end").alias("closed"), "items")


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """One event per id within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def window_bins(events: DataFrame, length: str, basis: tuple[str, ...], delay: str | None = "1 day") -> DataFrame:
    """(opened, mask, n): incremental bins of one fixed basis, where each event is a transaction of its type."""
    timely = events.withWatermark("ts", delay) if delay else events
    bit = F.lit(0)
    for p, item in enumerate(sorted(basis)):
        bit = bit + F.when(F.col("event_type") == item, F.lit(1 << p)).otherwise(F.lit(0))
    counted = timely.groupBy(F.window("ts", length).alias("w"), bit.alias("mask")).agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("opened"), "mask", "n")


def enriched(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join with an item dictionary (event_type, item_id) of bounded size."""
    return events.join(F.broadcast(dictionary), "event_type", "left")


def release_windows(counts: DataFrame, basis: tuple[str, ...], eps: float, noise: NoiseSource) -> DataFrame:
    """(opened, itemset, noisy_count): final bins of each window, completed, noised once and summed.  Disjoint windows share no transaction, so eps holds for all."""
    b = BasisSet.of([basis])
    spark = counts.sparkSession
    masks = spark.range(1 << b.length).select(F.col("id").cast("int").alias("mask"))
    # every seen window gets all its bins with 0, then its counts
    empty = counts.select("opened").distinct().crossJoin(F.broadcast(masks)).withColumn("n", F.lit(0).cast("long"))
    full = empty.unionByName(counts.select("opened", "mask", "n")).groupBy("opened", "mask").agg(F.sum("n").alias("n"))
    noisy = full.withColumn("noisy", F.col("n") + noise.laplace("window", 1 / eps, F.date_format("opened", "yyyy-MM-dd HH:mm:ss"), "mask"))
    low = noisy.select(F.col("opened").alias("o"), F.col("mask").alias("y"), "noisy")
    sums = masks.where("mask > 0").join(low, F.col("y").bitwiseAND(F.col("mask")) == F.col("mask")).groupBy(F.col("o").alias("opened"), "mask").agg(F.sum("noisy").alias("nc"))
    names = spark.createDataFrame([(m, "|".join(x for p, x in enumerate(b.bases[0]) if m >> p & 1)) for m in range(1, 1 << b.length)], "mask int, itemset string")
    return sums.join(F.broadcast(names), "mask").select("opened", "itemset", F.round("nc", 6).alias("noisy_count"))


def drain(stream: DataFrame, path: str) -> DataFrame:
    """Runs an appending stream over what is there into a table of files, and reads that; path must be one that all executors reach."""
    query = stream.writeStream.outputMode("append").trigger(availableNow=True).format("parquet").option("checkpointLocation", f"{path}/state").start(f"{path}/rows")
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/rows")


def release_stream(counts: DataFrame, basis: tuple[str, ...], eps: float, noise: NoiseSource, path: str) -> DataFrame:
    """Releases every window of a stream of final bins (opened, mask, n) as it closes, batch by batch, into a table of files.

    A batch that is run again after a failure replaces its own part of the
    table with the same draws, so no window is published with two noises.
    """

    def publish(batch: DataFrame, number: int) -> None:
        release_windows(batch, basis, eps, noise).write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    release_windows(counts.sparkSession.createDataFrame([], counts.schema), basis, eps, noise).write.parquet(f"{path}/rows/batch=-1")  # a stream without rows leaves an empty table
    query = counts.writeStream.outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}/state").foreachBatch(publish).start()
    query.awaitTermination()
    return counts.sparkSession.read.schema("opened timestamp, itemset string, noisy_count double").parquet(f"{path}/rows")


def running_item_counts(events: DataFrame, most: int = 10_000) -> DataFrame:
    """(user_id, n_events, n_kinds): running totals of each user, kept as state of our own: how many events, and which kinds of them.

    In update mode a user has a row for each batch that has events of theirs.
    The kinds of a user are as many as the public domain has; beyond ``most``
    the state refuses.
    """

    def update(key: tuple, groups: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, kinds = state.get if state.exists else (0, "")
        seen = set(kinds.split("|")) - {""}
        for g in groups:
            n += len(g)
            seen.update(g["event_type"].dropna())
        if len(seen) > most:
            raise ValueError("a user has more kinds of events than the domain allows")
        state.update((n, "|".join(sorted(seen))))
        yield pd.DataFrame({"user_id": [key[0]], "n_events": [n], "n_kinds": [len(seen)]})

    out, kept = "user_id long, n_events long, n_kinds long", "n long, kinds string"
    return events.groupBy("user_id").applyInPandasWithState(update, out, kept, "update", GroupStateTimeout.NoTimeout)


def drain_updates(stream: DataFrame, path: str) -> DataFrame:
    """Runs an updating stream over what is there; (batch, rows) of all its batches as a table."""

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    stream.sparkSession.createDataFrame([], stream.schema).write.parquet(f"{path}/rows/batch=-1")
    query = stream.writeStream.outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{path}/state").foreachBatch(keep).start()
    query.awaitTermination()
    return stream.sparkSession.read.parquet(f"{path}/rows")
