"""The corpus pipeline: quality, line dedup, near-dedup, decontamination, packing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept
and returns a DataFrame that is written as Parquet and read again.  All but the
last return the columns of documents.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from dp_itemsets.llm import decontamination, lines, nearcopies, packing, quality
from dp_itemsets.llm.catalog import tokenizer_path
from dp_itemsets.llm.common import remove_folder, shared_folder, table
from dp_itemsets.session import ship_package

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the classifier rejects."""
    ship_package(spark)
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def remove_repeated_chunks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts globally repeated chunks of lines out of the texts; every row stays."""
    ship_package(spark)
    return lines.remove_repeats(docs)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each component of texts whose fingerprints link, or whose five-word shingles are similar by 0.8 or more."""
    ship_package(spark)
    return nearcopies.keep_first(docs, by_fingerprint=True)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold benchmark passages."""
    ship_package(spark)
    return decontamination.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places the tokens of what is left into sequences."""
    ship_package(spark)
    return packing.pack_documents(docs, tokenizer_path())


STAGES: list[tuple[str, Stage]] = [
    ("quality", keep_quality),
    ("line_dedup", remove_repeated_chunks),
    ("near_dedup", keep_one_of_near_copies),
    ("decontamination", drop_contaminated),
    ("packing", pack),
]

#: SQL has neither the classifier nor the packing; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents, through Parquet in the shared folder.

    Packing checkpoints its pieces before it returns, so what the stages before
    it wrote is removed at the end.
    """
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    try:
        for k, (name, stage) in enumerate(STAGES):
            docs = stage(spark, docs, sf_dir)
            if k < len(STAGES) - 1:
                docs.write.parquet(f"{folder}/{k}-{name}")
                docs = spark.read.parquet(f"{folder}/{k}-{name}")
    finally:
        remove_folder(spark, folder)
    return docs
