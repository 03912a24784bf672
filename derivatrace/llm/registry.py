"""The queries of the ten operators, and the SQL that DuckDB can hold them against."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from derivatrace.llm import decontam, licenses, mixing, oracles, quality, secret_scan, simhash, spans, token_counts, token_output, url_filter
from derivatrace.llm.common import documents


TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")
PIECES = public_tokenizers.path("piece_bpe_32k.model")


def op1_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.token_digests(documents(spark, sf_dir), tokenizer=TOKENIZER)


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(documents(spark, sf_dir), vocabulary=PIECES)


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_report(documents(spark, sf_dir))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans as text: label:first word:words:edits, comma-joined."""
    found = licenses.license_scan(documents(spark, sf_dir))
    return found.withColumn("spans", F.array_join(F.transform("spans", lambda s: F.concat_ws(":", s["label"], s["word"], s["words"], s["edits"])), ","))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_rules(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")).drop("reasons")


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.secret_scan(documents(spark, sf_dir))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.url_filter(spark.read.parquet(f"{sf_dir}/pages.parquet")).drop("purity")


def op10_sentence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spans.dedup_spans(documents(spark, sf_dir))


OPERATORS = (op1_packed_ids, op2_token_counts, op3_source_mix, op4_decontamination, op5_license_scan, op6_simhash, op7_quality_rules, op8_secret_scan, op9_url_filter, op10_sentence_spans)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in OPERATORS}


def oracle_sql() -> dict[str, str]:
    """The others (tokeniser, trie, fuzzy matching, fingerprints, character models, sentence hashes) are tested by brute force."""
    return {"op3_source_mix": oracles.mix(), "op4_decontamination": oracles.contamination(), "op7_quality_rules": oracles.quality_rules(), "op9_url_filter": oracles.urls()}
