"""A training corpus from ``documents``: five stages, each written as Parquet and read by the next.

1. quality rules: rows that the rules or the isolation forest reject go;
2. n-gram Jaccard join: of near copies the one with the smallest doc_id stays;
3. PII: spans found are replaced by their kind in angle brackets;
4. mixing: rows are repeated or left out, so that sources have their target words;
5. BPE: token ids with their digests, and the digest of the decoded text.

Stages 1 to 4 return the columns of documents (and any others the input has). A stage reads the labels,
where it needs them, from ``sf_dir``. Empty tables, nulls and repeated rows: as in the operators.
Before a stage, executors hand back the memory of the one before.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from saferoute.llm import bpe_automaton, common, mixing, ngram_join, pii, quality


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    common.release(spark)
    return quality.kept_rows(docs, common.table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    common.release(spark)
    return ngram_join.representatives(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    common.release(spark)
    return pii.masked(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    common.release(spark)
    return bpe_automaton.encode(docs)


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("mix", mix), ("tokens", tokens)]

#: SQL can't express the forest, the join's components at size, or the tokenizer; tests/llm has brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole of ``documents``."""
    docs = common.table(spark, sf_dir, "documents")
    folder = f"{common.shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
