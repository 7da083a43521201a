"""Transaction files: one transaction a line (items separated by blanks), CSV, JSON lines; and result sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .transactions import Transactions


def read_lines(spark: SparkSession, path: str, separator: str = " ") -> Transactions:
    """The format of public itemset corpora.  Lines have no ids, so each gets one; blank lines are empty transactions."""
    items = F.sort_array(F.array_distinct(F.filter(F.split(F.trim("value"), separator), lambda x: x != "")))
    return Transactions(spark.read.text(path).select(F.monotonically_increasing_id().alias("tid"), items.alias("items")))


def write_lines(tx: Transactions, path: str, separator: str = " ") -> None:
    """Items that hold the separator don't survive this format and are refused."""
    if not tx.rows.where(F.exists("items", lambda i: i.contains(separator))).isEmpty():
        raise ValueError("an item holds the separator")
    tx.rows.select(F.array_join("items", separator).alias("value")).write.mode("overwrite").text(path)


def read_csv(spark: SparkSession, path: str, tid: str = "tid", item: str = "item") -> Transactions:
    return Transactions.from_long(spark.read.schema(f"{tid} string, {item} string").option("header", True).csv(path), tid, item)


def read_json(spark: SparkSession, path: str) -> Transactions:
    rows = spark.read.schema("tid string, items array<string>").json(path)
    return Transactions(rows.select("tid", F.sort_array(F.array_distinct("items")).alias("items")))


def write_table(tx: Transactions, name: str, buckets: int = 8) -> None:
    """A table of (tid, item), bucketed by tid so that grouping or joining by transaction needs no shuffle."""
    tx.rows.select("tid", F.explode_outer("items").alias("item")).write.mode("overwrite").bucketBy(buckets, "tid").sortBy("tid").saveAsTable(name)


def read_table(spark: SparkSession, name: str) -> Transactions:
    return Transactions.from_long(spark.table(name))


def write_release(release: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None) -> None:
    writer = release.write.mode("overwrite")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.format(fmt).option("header", True).save(path)
