"""From raw documents to token ids: five stages, each written as Parquet before the next reads it.

Rows that repeat a doc_id are rows of their own in every stage. Null texts pass all filters and end
as documents without ids; empty tables pass as empty tables; other columns than those of
`documents` are carried as they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from kgtrail.llm import op2_decontaminate, op6_pii, op8_near_copies, op10_toxicity
from kgtrail.llm.common import executors_give_back, stored, table
from kgtrail.llm.op1_bpe import encode_documents, tokenizer_file


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the model, learned from the labels of those given, scores under one half."""
    return op10_toxicity.reject(docs, op10_toxicity.learn(docs, table(spark, sf_dir, "labels")))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies: the one with the smallest doc_id. What is left to run
    of its plan has no Python, and decontamination may run none, so the workers give back here."""
    executors_give_back(spark)
    kept = op8_near_copies.without_near_copies(docs)
    executors_give_back(spark)
    return kept


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which passages of the benchmark make up less than a twentieth; no Python runs on the
    executors."""
    executors_give_back(spark, workers=False)
    return op2_decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced by its kind."""
    executors_give_back(spark)
    return op6_pii.redact(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, and a hash of what the ids decode to."""
    executors_give_back(spark)
    return encode_documents(docs, tokenizer_file(), form="ids")


STAGES = [
    ("toxicity", toxicity),
    ("near_copies", near_copies),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("token_ids", token_ids),
]
#: Learning, components and merges have no SQL form; tests hold run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
