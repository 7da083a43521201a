"""Queries that apply the operators to the given tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, language, licenses, lines, lm, media, packing, quality, sharding, simhash
from .common import table

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("item_ids")


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify_languages(table(spark, sf_dir, "documents"), vocabulary_path())


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents"), 24)


def op5_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def op6_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_documents(table(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.components(table(spark, sf_dir, "documents"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.dedup_lines(table(spark, sf_dir, "documents"))


def op10_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.document_media(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Query]:
    return {
        "op1_decontamination": op1_decontamination,
        "op2_quality": op2_quality,
        "op3_language": op3_language,
        "op4_sharding": op4_sharding,
        "op5_licenses": op5_licenses,
        "op6_lm": op6_lm,
        "op7_packing": op7_packing,
        "op8_simhash": op8_simhash,
        "op9_line_dedup": op9_line_dedup,
        "op10_media": op10_media,
    }


_LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_WORDS = rf"regexp_extract_all(translate(coalesce(text, ''), '{_LETTERS}', '{_LETTERS.lower()}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

#: Windows by text, places by list slices: the plain way, which only small tables allow.
OP1_SQL = f"""WITH i AS (SELECT item_id, {_WORDS} AS w FROM benchmark), n AS (SELECT item_id, w, least(len(w), 13) AS size FROM i WHERE len(w) > 0),
    wins AS (SELECT DISTINCT item_id, size, array_to_string(list_slice(w, k + 1, k + size), ' ') AS win FROM (SELECT *, unnest(range(0, len(w) - size + 1)) AS k FROM n)),
    d AS (SELECT doc_id, {_WORDS} AS w FROM documents), sizes AS (SELECT DISTINCT size FROM wins),
    p AS (SELECT doc_id, w, size, unnest(range(0, len(w) - size + 1)) AS k FROM d, sizes WHERE len(w) >= size),
    hits AS (SELECT p.doc_id, p.k, p.size, wins.item_id FROM (SELECT doc_id, k, size, array_to_string(list_slice(w, k + 1, k + size), ' ') AS win FROM p) p JOIN wins USING (size, win)),
    covered AS (SELECT doc_id, count(DISTINCT place) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + size)) AS place FROM hits) GROUP BY doc_id),
    items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM hits) GROUP BY doc_id)
    SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(c.n_hit, 0) AS n_hit, coalesce(x.n_items, 0) AS n_items, sha256(coalesce(x.names, '')) AS items_sha256,
        coalesce(c.n_hit, 0) > 0 AND 20 * coalesce(c.n_hit, 0) >= len(d.w) AS contaminated
    FROM d LEFT JOIN covered c USING (doc_id) LEFT JOIN items x USING (doc_id)"""


def oracle_sql() -> dict[str, str]:
    """Only the index lookup has an SQL twin; the rest needs CRC-32, XXH64, tokenizers or trained models."""
    return {"op1_decontamination": OP1_SQL}
