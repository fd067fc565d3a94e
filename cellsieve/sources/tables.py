"""Sources and sinks (O1, O2)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_transactions_text(spark: SparkSession, path: str) -> DataFrame:
    """(items array<int>) from text with one transaction of numbers a line; blank lines are dropped, repeats inside a line count once."""
    words = F.split(F.trim("value"), r"\s+")
    return spark.read.text(path).where(F.trim("value") != "").select(F.array_sort(F.array_distinct(words.cast("array<int>"))).alias("items"))


def write_transactions_text(tx: DataFrame, path: str) -> None:
    tx.select(F.array_join(F.col("items").cast("array<string>"), " ").alias("value")).write.text(path)


def write_patterns(patterns: DataFrame, path: str, by: tuple[str, ...] = ("size",), kind: str = "parquet") -> None:
    """A pattern store, partitioned so that filters on `by` skip files."""
    patterns.write.partitionBy(*by).format(kind).mode("overwrite").save(path)
