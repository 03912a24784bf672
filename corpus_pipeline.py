"""A corpus pipeline: quality rules, near-dedup, decontamination, mixing, packed token ids.

Each stage takes what its predecessor kept, whole, and its decisions take effect: rejected documents go, one document of
each near-duplicate group stays, documents that share a window with the benchmark go, documents are repeated or left
out as the mix says, and what is left is tokenised into packed files and read back as one digest row a document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from derivatrace.llm import decontam, mixing, quality, simhash, token_output
from derivatrace.llm.common import cut, documents
from derivatrace.llm.registry import TOKENIZER


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


def pack_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_output.token_digests(docs, tokenizer=TOKENIZER)


STAGES = [
    ("quality_rules", keep_quality),
    ("simhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_contaminated),
    ("source_mixing", mix_sources),
    ("packed_token_ids", pack_tokens),
]

#: SQL can't express fingerprints, fuzzy thresholds or the tokeniser; tests/llm/test_pipeline.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents, each one's result written to the shared folder and read again."""
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
