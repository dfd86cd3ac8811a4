"""Queries of the text operators, with production parameters, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from wavesum.llm.common import documents


def vocabulary(name: str) -> str:
    """The path of a public vocabulary file; WAVESUM_TOKENIZERS names another folder."""
    import os

    if folder := os.environ.get("WAVESUM_TOKENIZERS"):
        return f"{folder}/{name}"
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.scoring import scored

    return scored(documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.decontaminate import contaminated

    return contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.language import identify

    return identify(documents(spark, sf_dir).select("doc_id", "lang", "text"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.sharding import shard_documents

    return shard_documents(documents(spark, sf_dir).select("doc_id", "text"), shards=24)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.suffix_dedup import suffix_dedup_digest

    return suffix_dedup_digest(documents(spark, sf_dir))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.simhash import near_components

    return near_components(documents(spark, sf_dir))


def op7_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.sentencepieces import sentencepiece_digest

    return sentencepiece_digest(documents(spark, sf_dir), vocabulary("piece_bpe_32k.model"))


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.seed_dedup import seed_dedup_digest

    return seed_dedup_digest(documents(spark, sf_dir))


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.token_files import token_file_digest

    return token_file_digest(documents(spark, sf_dir), vocabulary("word_bpe_49k.json"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wavesum.llm.quality import quality_digest

    return quality_digest(documents(spark, sf_dir))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_lm_scoring, op2_decontamination, op3_language_id, op4_sharding, op5_suffix_dedup, op6_simhash, op7_sentencepiece, op8_substring_dedup, op9_token_files, op10_quality_rules)}


def oracle_sql() -> dict[str, str]:
    """Both substring dedups and the quality rules; the others' hashes, tokenizers and models aren't in SQL."""
    from wavesum.llm.oracles import SUBSTRING_DEDUP, SUFFIX_DEDUP, quality

    return {"op5_suffix_dedup": SUFFIX_DEDUP, "op8_substring_dedup": SUBSTRING_DEDUP, "op10_quality_rules": quality()}
