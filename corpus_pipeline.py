"""The corpus pipeline: quality filter, exact dedup, near-duplicate join, secret redaction, packing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns a frame; all but
the last return the columns of ``documents``.  ``run`` writes every stage to the shared checkpoint folder
and reads it again, as the check tool does.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.llm import bestfit_packing, content_sort, jaccard_join, quality_rules, secret_crf
from deltafold.session import checkpoint_folder


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble does not reject (score of 0.5 or more)."""
    model = quality_rules.train_for(spark, docs, sf_dir)
    score = "__quality_score"
    while score in docs.columns:
        score += "_"
    return quality_rules.scored(docs, model, [F.col(c) for c in docs.columns], name=score).where(F.col(score) >= 0.5).drop(score)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with equal normalised texts, the one with the smallest id."""
    return content_sort.keep_first_copies(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates, the document with the smallest id."""
    return jaccard_join.keep_first_of_classes(docs)


def secret_redaction(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their texts replaced and ``n_chars`` following."""
    return secret_crf.redacted_documents(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents' pieces in sequences of 2048 tokens."""
    return bestfit_packing.packed_documents(docs, public_tokenizers.path("word_bpe_49k.json"), with_ids=False)


STAGES = [
    ("quality_filter", quality_filter),
    ("exact_dedup", exact_dedup),
    ("near_dedup", near_dedup),
    ("secret_redaction", secret_redaction),
    ("packing", packing),
]

#: A fitted classifier and a tokenizer are stages that SQL cannot express; see tests/llm.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; the rows of the last."""
    folder = f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
