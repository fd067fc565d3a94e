"""The registered queries of the training-data operators, each over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import op01_secrets, op02_mixing, op03_licences, op04_embeddings, op05_minhash, op06_pii, op07_warc, op08_pieces, op09_sharding, op10_quality
from .common import table


def op1_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op01_secrets.find_secrets(table(spark, sf_dir, "documents"))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op02_mixing.mixed(table(spark, sf_dir, "documents"))


def op3_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op03_licences.find_licences(table(spark, sf_dir, "documents"))


def op4_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, class_id, links): every id with its class of near copies and its number of links."""
    return op04_embeddings.near_classes(table(spark, sf_dir, "embeddings")).selectExpr("id AS vec_id", "class AS class_id", "links")


def embedding_classes_with_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same operator where chains of near copies are sure to exist: each vector twice, and with the sign of the first, the second and both coordinates turned."""
    from pyspark.sql import functions as F

    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding")
    k = F.col("k")
    turned = F.transform("embedding", lambda x, i: F.when((i == 0) & k.isin(1, 3) | (i == 1) & k.isin(2, 3), -x).otherwise(x))
    copies = e.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(4)))).select((F.col("vec_id") + k * 100_000_000).alias("vec_id"), turned.alias("embedding"))
    return op04_embeddings.near_classes(copies).selectExpr("id AS vec_id", "class AS class_id", "links")


def embeddings_with_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Its pairs where near copies are sure to exist: each vector beside itself with the sign of one coordinate turned."""
    from pyspark.sql import functions as F

    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding")
    copies = e.select((F.col("vec_id") + 100_000_000).alias("vec_id"), F.transform("embedding", lambda x, i: F.when(i == 0, -x).otherwise(x)).alias("embedding"))
    return op04_embeddings.near_pairs(e.union(copies))


def op5_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, group_id, keep): every document with the document that stands for its group."""
    return op05_minhash.near_duplicates(table(spark, sf_dir, "documents")).selectExpr("id AS doc_id", "`group` AS group_id", "copies", "keep")


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op06_pii.find_personal(table(spark, sf_dir, "documents"))


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sidecar index of all pages, written as monolithic files and normalised."""
    return op07_warc.normalised_pages(table(spark, sf_dir, "pages"))


def op8_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op08_pieces.encode(table(spark, sf_dir, "documents"))


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op09_sharding.assign(table(spark, sf_dir, "documents"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op10_quality.judged(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_secrets": op1_secrets,
        "op2_mixing": op2_mixing,
        "op3_licences": op3_licences,
        "op4_embeddings": op4_embeddings,
        "embedding_classes_with_copies": embedding_classes_with_copies,
        "embeddings_with_copies": embeddings_with_copies,
        "op5_minhash": op5_minhash,
        "op6_pii": op6_pii,
        "op7_warc": op7_warc,
        "op8_pieces": op8_pieces,
        "op9_sharding": op9_sharding,
        "op10_quality_rules": op10_quality_rules,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_mixing": op02_mixing.mixed_sql(),
        "op4_embeddings": op04_embeddings.near_classes_sql(),
        "embedding_classes_with_copies": op04_embeddings.near_classes_sql(table="(SELECT vec_id + k * 100000000 AS vec_id, list_transform(embedding, lambda x, i: CASE WHEN i = 1 AND k IN (1, 3) OR i = 2 AND k IN (2, 3) THEN -x ELSE x END) AS embedding FROM embeddings, range(5) r(k))"),
        "embeddings_with_copies": op04_embeddings.near_pairs_sql(table="(SELECT vec_id, embedding FROM embeddings UNION ALL SELECT vec_id + 100000000, list_transform(embedding, lambda x, i: CASE WHEN i = 1 THEN -x ELSE x END) FROM embeddings)"),
        "op9_sharding": op09_sharding.assigned_sql(),
        "op10_quality_rules": op10_quality.judged_sql(),
    }
