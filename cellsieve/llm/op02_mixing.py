"""Mixing sources to target weights by systematic sampling.

A source of weight w shall make up w / (sum of weights) of the mixed characters.  Each of its documents is therefore expected
(w * all) / (sum of weights * source) times; the fraction is kept as two whole numbers, so no rounding adds up over the documents.  Within a source documents stand in the order of a seeded hash; one random offset is added to the running sum
of expected copies, and a document is emitted once for each integer that its stretch of the sum crosses, so every source gets its expected
number of copies to within one, and a document its own rounded up or down.

The running sum never puts a source into one task: rows fall into 4096 ranges of the hash, a small table holds the sum of each (source, range),
and only the rows of one range are ordered together.

Definitions for odd input.  A null source is a source of its own.  Null and empty texts have no characters, and are emitted like the other
documents of their source; a source without any character keeps each document once.  Ties of the hash go by doc_id, then by text; equal rows
are interchangeable.  Sources without a given weight have weight 1; a weight of 0 drops a source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Parts of each source in the mix; all others have one part.
WEIGHTS = {"src0": 4}
SEED = 17
UNIT = 1_000_000
WHOLE = "decimal(30,0)"


def offset(seed: int = SEED) -> int:
    """The random offset, in millionths."""
    return (seed * 2654435761 + 362437) % UNIT


def with_copies(docs: DataFrame, weights: dict[str, int], seed: int, id_col: str, text_col: str, source_col: str) -> DataFrame:
    """docs with __cs_copies, the number of times that each row is emitted."""
    weight: Column = F.lit(1)
    for name, w in sorted(weights.items()):
        weight = F.when(F.col("__cs_source") == name, F.lit(int(w))).otherwise(weight)
    # a null source gets a name that no other has: the others are prefixed
    source = F.coalesce(F.concat(F.lit("="), F.col(source_col).cast("string")), F.lit("null"))
    size = F.coalesce(F.length(F.col(text_col).cast("string")), F.lit(0)).cast("bigint")
    text = F.col(text_col).cast("string")
    hashed = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("null"))))
    keyed = docs.withColumns({"__cs_key": source, "__cs_hash": hashed, "__cs_range": F.substring(hashed, 1, 3)})
    sums = docs.select(source.alias("__cs_key"), size.alias("size"), F.substring(hashed, 1, 3).alias("__cs_range")).groupBy("__cs_key", "__cs_range").agg(F.count("*").alias("n"), F.sum("size").alias("size"))
    per = sums.groupBy("__cs_key").agg(F.sum("size").alias("size")).withColumn("__cs_source", F.when(F.col("__cs_key").startswith("="), F.expr("substring(__cs_key, 2)"))).withColumn("w", weight)
    total = per.agg(F.sum("size").cast("decimal(20,0)").alias("all_size"), F.sum("w").alias("all_w"))
    # expected copies of a document, times UNIT: up / down
    up = F.when(F.col("size") == 0, F.lit(UNIT)).otherwise(F.expr(f"{UNIT} * w * all_size")).cast(WHOLE)
    down = F.when(F.col("size") == 0, F.lit(1)).otherwise(F.expr("all_w * size")).cast(WHOLE)
    rates = per.crossJoin(total).select("__cs_key", F.when(F.col("w") == 0, F.lit(0)).otherwise(up).cast(WHOLE).alias("__cs_up"), down.alias("__cs_down"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("__cs_key").orderBy("__cs_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    bases = sums.join(rates, "__cs_key").select("__cs_key", "__cs_range", "__cs_up", "__cs_down", before.cast("bigint").alias("__cs_base"))
    order = Window.partitionBy("__cs_key", "__cs_range").orderBy("__cs_hash", F.col(id_col).asc_nulls_first(), F.md5(F.coalesce(text, F.lit(""))))
    placed = keyed.withColumn("__cs_nth", F.row_number().over(order)).join(bases, ["__cs_key", "__cs_range"])
    def crossed(k: str) -> str:  # whole numbers up to the end of document k of the source
        return f"(CAST({k} AS DECIMAL(18,0)) * __cs_up + {offset(seed)} * __cs_down) div (__cs_down * {UNIT})"

    return placed.withColumn("__cs_copies", F.expr(f"{crossed('(__cs_base + __cs_nth)')} - {crossed('(__cs_base + __cs_nth - 1)')}").cast("int"))


def mixed(docs: DataFrame, weights: dict[str, int] | None = None, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, source, copy): a row for each emission, copy counts from 1."""
    slim = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(source_col).cast("string").alias("source"))
    out = with_copies(slim, WEIGHTS if weights is None else weights, seed, "doc_id", "text", "source").where("__cs_copies > 0")
    return out.select("doc_id", "source", F.explode(F.sequence(F.lit(1), F.col("__cs_copies"))).alias("copy"))


def mix_documents(docs: DataFrame, weights: dict[str, int] | None = None, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of docs as often as they are emitted, with their columns as they were."""
    out = with_copies(docs, WEIGHTS if weights is None else weights, seed, id_col, text_col, source_col).where("__cs_copies > 0")
    return out.withColumn("__cs_copy", F.explode(F.sequence(F.lit(1), F.col("__cs_copies")))).select(*docs.columns)


def mixed_sql(weights: dict[str, int] | None = None, seed: int = SEED) -> str:
    weight = "CASE key " + " ".join(f"WHEN '={k}' THEN {int(w)}" for k, w in sorted((WEIGHTS if weights is None else weights).items())) + " ELSE 1 END"
    return f"""
WITH d AS (SELECT doc_id, source, coalesce('=' || source, 'null') AS key, coalesce(length(text), 0) AS size,
                  md5('{seed}:' || coalesce(CAST(doc_id AS VARCHAR), 'null')) AS h, md5(coalesce(text, '')) AS th FROM documents),
per AS (SELECT key, sum(size) AS size, {weight} AS w FROM d GROUP BY key),
total AS (SELECT sum(size) AS all_size, sum(w) AS all_w FROM per),
rates AS (SELECT key, CASE WHEN w = 0 THEN 0::HUGEINT WHEN size = 0 THEN {UNIT}::HUGEINT ELSE {UNIT}::HUGEINT * w * all_size END AS up, CASE WHEN size = 0 THEN 1::HUGEINT ELSE all_w::HUGEINT * size END AS down FROM per, total),
n AS (SELECT d.*, up, down, row_number() OVER (PARTITION BY d.key ORDER BY h, doc_id NULLS FIRST, th) AS k FROM d JOIN rates USING (key)),
c AS (SELECT doc_id, source, CAST((k * up + {offset(seed)} * down) // (down * {UNIT}) - ((k - 1) * up + {offset(seed)} * down) // (down * {UNIT}) AS BIGINT) AS copies FROM n)
SELECT doc_id, source, CAST(unnest(generate_series(1, copies)) AS INTEGER) AS copy FROM c WHERE copies > 0"""
