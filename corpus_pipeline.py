"""A corpus pipeline of five stages over ``documents``; each stage's rows are written as Parquet and read again by the next.

Toxic documents go, of equal texts one stays, of each group of near duplicates one stays, secrets are masked, and what is left
is packed into token windows. All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockdelta.llm import exact_dedup, ngram_join, packing, secrets, toxicity
from blockdelta.llm.common import staged, table
from blockdelta.llm.queries import TOXIC_FROM, tokenizer_file


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose score is below the threshold; learns from labelled documents of the input."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score_documents(docs, model, score_col="__toxicity")
    return scored.where(F.col("__toxicity") < TOXIC_FROM).select(*docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id stays."""
    return exact_dedup.mark_duplicates(docs, prefix="__dedup_").where("__dedup_kept").select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest doc_id stays."""
    found = ngram_join.near_duplicates(docs, links=False)
    losers = found.where(F.col("component_id") < F.col("doc_id")).select(F.col("doc_id").alias("__loser")).distinct()
    return docs.join(losers, F.col("doc_id") == F.col("__loser"), "left_anti")


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay; secrets in their texts are masked."""
    return secrets.redact(docs)


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row for each piece of a document, with its place in a token window."""
    import public_tokenizers

    return packing.pack(docs, tokenizer_file("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, tokenizer_file("byte_bpe_50k.json"))


STAGES = [("toxicity", drop_toxic), ("exact_dedup", drop_copies), ("ngram_join", drop_near_copies), ("secret_scan", mask_secrets), ("packing", pack_windows)]

#: Scoring, similarity joins and tokenising are beyond SQL; tests hold the stages' operators against brute force, and the pipeline against its stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = staged(docs, f"pipeline-{name}")
    return docs
