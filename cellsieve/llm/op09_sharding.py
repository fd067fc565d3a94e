"""Sharding by jump consistent hashing: stable keys to shards without a ring table.

A key's shard among n follows from the key alone by jumping ahead, in about ln n steps, through the shard counts at which the key would move.
When shards are appended, exactly the keys whose next jump lands on a new shard move, 1 - n / (n + m) of them on average, and none
moves between old shards.

Definitions for odd input.  Integer keys are hashed as they are (as unsigned 64-bit numbers); any other type by the first 64 bits of the MD5 of its text.
A null key goes to shard 0.  Equal keys share a shard, so repeated rows stay together.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

SHARDS = 1000
APPENDED = 24


def jump(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shards of uint64 keys; every key is followed until it jumps past the last shard."""
    key = keys.astype(np.uint64)
    out = np.zeros(len(key), np.int64)
    live = np.arange(len(key))
    ahead = np.zeros(len(key), np.int64)
    while len(live):
        out[live] = ahead
        key = key * np.uint64(2862933555777941757) + np.uint64(1)
        step = float(1 << 31) / ((key >> np.uint64(33)).astype(np.float64) + 1.0)
        ahead = ((ahead + 1).astype(np.float64) * step).astype(np.int64)
        on = ahead < shards
        live, ahead, key = live[on], ahead[on], key[on]
    return out


def shard_of(key: Column, shards: int) -> Column:
    """Shard of a bigint key column, by Arrow batches."""
    if shards < 1:
        raise ValueError("there must be a shard")

    @F.pandas_udf(T.IntegerType())
    def run(k: pd.Series) -> pd.Series:
        return pd.Series(jump(k.to_numpy(np.int64).view(np.uint64), shards).astype(np.int32))

    return F.when(key.isNull(), F.lit(0)).otherwise(run(F.coalesce(key, F.lit(0).cast("bigint"))))


def numeric_key(df: DataFrame, key_col: str) -> Column:
    kind = df.schema[key_col].dataType
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return F.col(key_col).cast("bigint")
    half = [F.conv(F.substring(F.md5(F.col(key_col).cast("string")), 1 + 8 * i, 8), 16, 10).cast("bigint") for i in (0, 1)]
    return F.shiftleft(half[0], 32).bitwiseOR(half[1])


def assign(df: DataFrame, key_col: str = "doc_id", shards: int = SHARDS, appended: int = APPENDED) -> DataFrame:
    """(key, shard, shard_after): the shard of every row among `shards`, and among `shards + appended`."""
    key = numeric_key(df, key_col)
    return df.select(F.col(key_col), shard_of(key, shards).alias("shard"), shard_of(key, shards + appended).alias("shard_after"))


def write_shards(df: DataFrame, path: str, key_col: str = "doc_id", shards: int = SHARDS, parts: int = 1) -> None:
    """df as Parquet under path, one folder a shard; a shuffle by shard and by a hash of the key gives each shard to `parts` tasks, so that a large shard is
    no single task's work."""
    name, part = "__cellsieve_shard", "__cellsieve_part"
    keyed = df.withColumn(name, shard_of(numeric_key(df, key_col), shards)).withColumn(part, F.pmod(F.xxhash64(F.lit("part"), F.col(key_col)), F.lit(parts)))
    keyed.repartition(shards * parts, name, part).drop(part).write.partitionBy(name).parquet(path)


def assigned_sql(shards: int = SHARDS, appended: int = APPENDED, table: str = "documents", key: str = "doc_id") -> str:
    def part(n: int, name: str) -> str:
        return f"""
{name}(id, b, j, k) AS (
  SELECT {key}, CAST(-1 AS BIGINT), CAST(0 AS BIGINT), CASE WHEN {key} < 0 THEN CAST({key} AS HUGEINT) + 18446744073709551616 ELSE CAST({key} AS HUGEINT) END FROM keys
  UNION ALL
  SELECT id, j, CAST(floor(CAST(j + 1 AS DOUBLE) * (2147483648.0::DOUBLE / (CAST(CAST(k2 // 8589934592 AS BIGINT) AS DOUBLE) + 1.0::DOUBLE))) AS BIGINT), k2
  FROM (SELECT id, j, (k * 2862933555777941757 + 1) % 18446744073709551616 AS k2 FROM {name} WHERE j < {n}))"""

    return f"""
WITH RECURSIVE keys AS (SELECT DISTINCT {key} FROM {table} WHERE {key} IS NOT NULL),{part(shards, "one")},{part(shards + appended, "two")},
s1 AS (SELECT id, CAST(max(j) AS INTEGER) AS shard FROM one WHERE j < {shards} GROUP BY id),
s2 AS (SELECT id, CAST(max(j) AS INTEGER) AS shard FROM two WHERE j < {shards + appended} GROUP BY id)
SELECT t.{key}, coalesce(s1.shard, 0) AS shard, coalesce(s2.shard, 0) AS shard_after
FROM {table} t LEFT JOIN s1 ON t.{key} = s1.id LEFT JOIN s2 ON t.{key} = s2.id"""
