"""Corpus preparation: quality rules, near-duplicate removal, secret redaction, mixing of sources, piece encoding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cellsieve.llm import op01_secrets, op02_mixing, op05_minhash, op08_pieces, op10_quality
from cellsieve.llm.common import table, written


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go; see op10_quality for nulls and empty texts."""
    return op10_quality.filter_documents(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays; see op05_minhash."""
    return op05_minhash.dedup_documents(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced in the texts; see op01_secrets."""
    return op01_secrets.redact_documents(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are dropped and repeated until sources have their weights; see op02_mixing."""
    return op02_mixing.mix_documents(docs)


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, ids, n_ids, exact) of every document; see op08_pieces."""
    return op08_pieces.encode(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("secrets", secrets), ("mixing", mixing), ("pieces", pieces)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what a stage returns is written in the shared folder and read again for the next."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs, f"stage-{name}")
    return docs


#: SQL has neither the signatures nor the pieces; tests/llm/test_pipeline.py holds run() against brute force.
ORACLE_SQL = None
