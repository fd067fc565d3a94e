"""Choice of the oracle, and rewrites that come before Catalyst's (M27, 4.1)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.mining import condense, without_infrequent
from ..operators.search import BROADCAST_BYTES
from ..spec import Constraints

#: Patterns that the relational plan is meant for.
RELATIONAL_PATTERNS = 100_000_000


@dataclass(frozen=True)
class OraclePlan:
    kind: str
    reason: str


def rewrite(tx: DataFrame, c: Constraints) -> DataFrame:
    """Constraints pushed into the data: transactions that lack a required item go only where all supports are asked above it, items that may not occur
    and infrequent items go before anything is joined (K7).  Supports of patterns that meet the constraints do not change."""
    out = tx
    for i in c.must:
        out = out.where(F.array_contains("items", i))
    if c.must_not and not c.closed:
        out = out.withColumn("items", F.array_except("items", F.array(*[F.lit(i) for i in c.must_not])))
    if c.minsup and c.minsup > 1 and not c.closed:
        out = without_infrequent(out, c.minsup)
    return out


def choose_oracle(tx: DataFrame, c: Constraints, patterns: int | None = None) -> OraclePlan:
    """relational where the patterns are known to fit a table; else a search oracle by broadcast where the condensed bitmaps fit; else sharded
    by first items where a branch is expected to fit; else block by block."""
    if patterns is not None and patterns <= RELATIONAL_PATTERNS:
        return OraclePlan("relational", f"{patterns} patterns fit a table")
    n = condense(rewrite(tx, c)).agg(F.count("*").alias("rows"), F.coalesce(F.sum(F.size("items")), F.lit(0)).alias("ones")).first()
    size = n["ones"] * 24 + n["rows"] * 64
    generic = c.closed or c.must or c.must_not or c.implies or c.one_per_attribute
    if size <= BROADCAST_BYTES:
        return OraclePlan("generic" if generic else "tidset", f"{size} bytes of condensed data are broadcast")
    # a branch is searched inside one Python worker, where an item of a transaction costs about 100 bytes before it is packed
    most = tx.select(F.explode("items").alias("i")).groupBy("i").agg(F.count("*").alias("n")).agg(F.max("n").alias("most")).first()["most"] or 0
    longest = tx.agg(F.max(F.size("items"))).first()[0] or 0
    if most * longest * 100 <= BROADCAST_BYTES:
        return OraclePlan("sharded", "the largest branch fits a task; it knows every constraint")
    return OraclePlan("block", "even a branch exceeds a task; it knows every constraint")
