"""Sharding by rendezvous hashing.

Every record scores every shard with a hash of (record key, shard number) and
goes to the highest score.  A weighted shard of weight ``w`` scores
``-w / ln(u)`` with ``u`` uniform in (0, 1), so that its share of the keys is
``w`` over the sum of weights.  The score of an existing shard doesn't change
when shards are added, so records move only into new shards.

The hash is a prefix of SHA-256 so that any engine can repeat it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed


def uniform(key: Column, shard: int, seed: int = 0) -> Column:
    """Uniform in (0, 1) from the key's text, the shard number and a seed; a null key counts as the empty text."""
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(str(shard)), F.coalesce(key.cast("string"), F.lit("")))
    return (F.conv(F.substring(F.sha2(text, 256), 1, 13), 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))


def best_shard(key: Column, shards: int, weights: list[float] | None = None, seed: int = 0) -> Column:
    """Number of the shard with the highest score; ties go to the lower number."""
    weights = weights or [1.0] * shards
    if len(weights) != shards or min(weights) < 0 or max(weights) <= 0:
        raise ValueError("one weight of 0 or more for each shard, and one above 0, is needed")
    scores = [F.struct((-F.lit(float(w)) / F.log(uniform(key, s, seed))).alias("score"), F.lit(-s).alias("minus")) for s, w in enumerate(weights) if w > 0]
    best = F.greatest(*scores) if len(scores) > 1 else scores[0]
    return (-best["minus"]).cast("int")


def assign(docs: DataFrame, key: str = "doc_id", shards: int = 24, weights: list[float] | None = None, seed: int = 0) -> DataFrame:
    """All columns of ``docs`` behind ``shard`` and ``grown_shard`` (with one more shard of the mean weight).

    Rows with a null key share one shard.  Repeated keys share a shard.
    """
    grown = [*weights, sum(weights) / shards] if weights else None
    shard = best_shard(F.col(key), shards, weights, seed)
    # the grown choice compares the old winner with the new shard only
    w = grown or [1.0] * (shards + 1)

    def score(n: Column | int, weight: Column) -> Column:
        text = F.concat_ws(":", F.lit(str(seed)), (n if isinstance(n, Column) else F.lit(str(n))).cast("string"), F.coalesce(F.col(key).cast("string"), F.lit("")))
        u = (F.conv(F.substring(F.sha2(text, 256), 1, 13), 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))
        return -weight / F.log(u)

    old = F.element_at(F.array(*[F.lit(float(x)) for x in w]), F.col("shard") + 1)
    moved = F.when(score(shards, F.lit(float(w[-1]))) > score(F.col("shard"), old), F.lit(shards)).otherwise(F.col("shard"))
    return docs.select(shard.alias("shard"), *docs.columns).withColumn("grown_shard", moved.cast("int"))


def shard_documents(docs: DataFrame, shards: int = 24, weights: list[float] | None = None, seed: int = 0) -> DataFrame:
    """One row per document: its size, text checksum, shard and gapless slot within the shard.

    A null text has no bytes (size 8, checksum 0).  Slots follow doc_id (nulls
    first), then checksum, then size; fully equal rows take neighbouring slots
    in any order.  Rows are range-partitioned with a row number as last sort
    key, so a repeated id is spread over tasks like any other rows, and a slot
    is a local position plus the rows of earlier partitions.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + F.lit(8)).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    keyed = assign(rows, "doc_id", shards, weights, seed).withColumn("tie", F.monotonically_increasing_id())
    order = ["shard", "doc_id", "text_crc32", "size", "tie"]
    placed = checkpointed(
        keyed.repartitionByRange(*order).sortWithinPartitions(*order)
        .select("doc_id", "size", "text_crc32", "shard", "grown_shard", F.monotonically_increasing_id().alias("place"))
        .withColumn("part", F.shiftrightunsigned("place", 33))
    )
    # a row for each shard of each partition: partitions + shards rows at most, because partitions hold ranges
    runs = placed.groupBy("shard", "part").agg(F.count("*").alias("rows"), F.min("place").alias("first"))
    earlier = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = runs.select("shard", "part", "first", F.coalesce(F.sum("rows").over(earlier), F.lit(0)).alias("before"))
    return placed.join(F.broadcast(offsets), ["shard", "part"]).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard",
        (F.col("place") - F.col("first") + F.col("before")).cast("long").alias("slot"), "grown_shard",
    )
