"""The corpus pipeline: quality rules, near-duplicates, decontamination, mixing, token ids, each over all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from paramstore.llm import decontaminate, mixing, quality_rules, simhash, token_store
from paramstore.llm.common import shared_folder, table
from paramstore.llm.queries import MIX_WEIGHTS, mix_domain, tokenizer_file


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep(docs)


def dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove(docs, table(spark, sf_dir, "benchmark"), mode="documents")


#: No document goes in the mixing stage: rates of one and more, and as many tokens in all as they need to reach the weights.
MIX_OPTIONS = {"budget": None, "least": 1.0}


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats documents until the expected tokens have the weights; where no repeating reaches them, it warns and comes as near as it can."""
    return mixing.apply_copies(docs, mixing.mix(docs, table(spark, sf_dir, "labels"), mix_domain(), MIX_WEIGHTS, **MIX_OPTIONS))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    path = shared_folder(spark, "tokens")
    token_store.write_tokens(docs, path, tokenizer_file())
    return token_store.digests(token_store.read_tokens(spark, path))


STAGES = [("quality rules", quality), ("SimHash near-dedup", dedup), ("benchmark decontamination", clean), ("mixing to target weights", mix), ("token ids", tokens)]

#: The model, components and rates of the stages can't be said in SQL; tests/llm holds run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = shared_folder(spark, "stage")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
