"""The registered queries of the document operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, exact, media, neardup, packing, quality, sharding, suffix, tokencounts, toxicity
from .common import table


def op1_tiff_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_round_trip(table(spark, sf_dir, "documents"))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit_packing(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.exact_dedup(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = bpe.tokenizer_json(bpe.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken")))
    return bpe.round_trip(table(spark, sf_dir, "documents"), spec, public_tokenizers.PATTERN)


def op5_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.importance_resample(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_uniform_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.shuffled_shards(table(spark, sf_dir, "documents"), shards=16)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"))


def op8_toxic_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencounts.edited_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN)


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.repeat_digests(table(spark, sf_dir, "documents"))


_FOLDED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_tiff_pages, op2_best_fit_packing, op3_exact_dedup, op4_byte_bpe, op5_importance_resampling, op6_uniform_shards, op7_near_duplicates, op8_toxic_passages, op9_token_counts, op10_suffix_dedup)}


def oracle_sql() -> dict[str, str]:
    return {
        "op3_exact_dedup": f"""
            WITH t AS (SELECT doc_id, sha256({_FOLDED}) AS text_sha256 FROM documents),
                 g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY ALL)
            SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM t JOIN g USING (text_sha256)""",
    }
