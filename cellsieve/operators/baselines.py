"""Baselines (B1-B10): ideal, two-step, scan, flip chain, lattice walk, concept walk.

Draws over tables use weighted_draw: rows stand in the order of a hash of their key; a table of 4096 hash ranges holds the sums of integer weights,
a draw finds its range there, then its row inside the range.  No window passes all rows through one task.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import draw, share_of, two_to
from ..functions.lineage import cut
from ..spec import Data, MiningTask
from .cells import SAMPLE_SEED, weighted
from .oracles import Search


def weighted_draw(rows: DataFrame, key: str, weight: str, draws: DataFrame, uniform: Column) -> DataFrame:
    """draws joined with the row whose stretch of the running weights holds the draw's share of all weight."""
    keyed = rows.withColumn("h", F.md5(F.col(key).cast("string"))).withColumn("part", F.substring("h", 1, 3))
    local = keyed.withColumn("stop", F.sum(weight).over(Window.partitionBy("part").orderBy("h", key).rowsBetween(Window.unboundedPreceding, 0)))
    parts = keyed.groupBy("part").agg(F.sum(weight).alias("part_weight"))
    parts = parts.withColumn("part_stop", F.sum("part_weight").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)))  # 4096 rows at most
    total = parts.agg(F.max("part_stop").alias("total"))
    at = draws.crossJoin(F.broadcast(total)).withColumn("r", share_of(uniform, F.col("total")))
    placed = at.join(F.broadcast(parts), (F.col("r") >= F.col("part_stop") - F.col("part_weight")) & (F.col("r") < F.col("part_stop")))
    placed = placed.withColumn("r", F.col("r") - (F.col("part_stop") - F.col("part_weight"))).drop("part_stop", "part_weight", "total")
    return placed.join(local.drop("h"), "part").where((F.col("r") >= F.col("stop") - F.col(weight)) & (F.col("r") < F.col("stop"))).drop("part", "r", "stop")


def ids(spark: SparkSession, n: int, name: str) -> DataFrame:
    return spark.range(n).select(F.col("id").alias(name))


def ideal_sample(patterns: DataFrame, quality: str, n: int, seed: int = SAMPLE_SEED) -> DataFrame:
    """(sample_id, pattern) from the exact law (B1)."""
    u = draw(F.lit(seed), F.lit("ideal"), F.col("sample_id"))
    return weighted_draw(weighted(patterns, quality).select("pattern", "w"), "pattern", "w", ids(patterns.sparkSession, n, "sample_id"), u).select("sample_id", "pattern")


def picked(items: str, bits: Column) -> Column:
    """The items whose bit is set."""
    return F.filter(items, lambda x, i: F.expr("0").cast("bigint") != F.call_function("shiftright", bits, i).bitwiseAND(F.lit(1).cast("bigint")))


def two_step_candidates(tx: DataFrame, n: int, power: int = 1, seed: int = SAMPLE_SEED) -> DataFrame:
    """(candidate, pattern): pattern is null where the candidate is dropped at once.

    power 1: a transaction by multiplicity * (2^length - 1), then one of its non-empty subsets.  power 4: four transactions, the first by
    multiplicity * 2^length, the others by multiplicity, kept with probability 2^(common - first), then a subset of what they share; its law is the fourth power of the
    frequency.  Up to 40 items weights are exact; with longer transactions they are counted in units of 2^(longest - 40), so that a transaction
    whose share is below about 2^-40 of the longest one's is never drawn, and each item of the subset has a coin of its own."""
    spark = tx.sparkSession
    rows = tx.groupBy("items").agg(F.count("*").alias("mult")).withColumn("t", F.array_join("items", ","))
    longest = rows.agg(F.max(F.size("items"))).first()[0] or 0
    cand = ids(spark, n, "candidate")
    key = lambda what: draw(F.lit(seed), F.lit(what), F.col("candidate"))
    if longest > 40:
        return long_candidates(rows, longest, cand, key, power)
    every = two_to(F.size("items"))
    if power == 1:
        got = weighted_draw(rows.withColumn("w", F.col("mult") * (every - 1)).where("w > 0"), "t", "w", cand, key("tx"))
        got = got.withColumn("bits", F.pmod(key("subset"), two_to(F.size("items")) - 1) + 1)
        return got.select("candidate", F.array_join(picked("items", F.col("bits")), ",").alias("pattern"))
    got = weighted_draw(rows.withColumn("w", F.col("mult") * every), "t", "w", cand, key("tx1")).select("candidate", F.col("items").alias("i1"))
    common, first = F.col("i1"), F.size("i1")
    for k in range(2, power + 1):
        nxt = weighted_draw(rows, "t", "mult", cand, key(f"tx{k}")).select("candidate", F.col("items").alias(f"i{k}"))
        got = got.join(nxt, "candidate")
        common = F.array_intersect(common, F.col(f"i{k}"))
    got = got.withColumn("common", F.array_sort(common)).withColumn("kept", F.pmod(key("keep"), two_to(first - F.size("common"))) == 0)
    got = got.withColumn("bits", F.pmod(key("subset"), two_to(F.size("common"))))
    return got.select("candidate", F.when(F.col("kept") & (F.col("bits") > 0), F.array_join(picked("common", F.col("bits")), ",")).alias("pattern"))


def long_candidates(rows: DataFrame, longest: int, cand: DataFrame, key, power: int) -> DataFrame:
    scaled = rows.withColumn("w", F.floor(F.col("mult") * F.pow(F.lit(2.0), F.size("items") - longest + 40)).cast("bigint")).where("w > 0")
    got = weighted_draw(scaled, "t", "w", cand, key("tx1")).select("candidate", F.col("items").alias("common"))
    first = F.size("common")
    got = got.withColumn("first", first)
    for k in range(2, power + 1):
        nxt = weighted_draw(rows, "t", "mult", cand, key(f"tx{k}")).select("candidate", F.col("items").alias("next"))
        got = got.join(nxt, "candidate").withColumn("common", F.array_sort(F.array_intersect("common", "next"))).drop("next")
    coin = lambda what, i: F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(what), F.col("candidate").cast("string"), i)), 1, 1), 16, 10).cast("int") % 2 == 0
    kept = F.forall(F.sequence(F.lit(1), F.col("first") - F.size("common")), lambda i: coin("keep", i.cast("string"))) if power > 1 else F.lit(True)
    kept = F.when(F.col("first") == F.size("common"), F.lit(True)).otherwise(kept)
    subset = F.filter("common", lambda x: coin("subset", x))
    return got.select("candidate", F.when(kept & (F.size(subset) > 0), F.array_join(subset, ",")).alias("pattern"))


def two_step_until(tx: DataFrame, patterns: DataFrame, n: int, max_candidates: int, power: int = 1, batch: int = 100_000, seed: int = SAMPLE_SEED) -> tuple[DataFrame | None, int, int]:
    """(accepted samples, how many, candidates tried): candidates in batches until n are accepted or max_candidates are tried."""
    found, tried, kept = None, 0, 0
    while kept < n and tried < max_candidates:
        size = min(batch, max_candidates - tried)
        got = cut(two_step_sample(tx, patterns, size, power, seed * 1_000 + tried // batch).where("accepted").select((F.col("candidate") + tried).alias("candidate"), "pattern"))
        tried, kept = tried + size, kept + got.count()
        found = got if found is None else found.union(got)
    return found, kept, tried


def two_step_sample(tx: DataFrame, patterns: DataFrame, n: int, power: int = 1, seed: int = SAMPLE_SEED) -> DataFrame:
    """(candidate, pattern, accepted): candidates that are among the valid patterns are accepted."""
    c = two_step_candidates(tx, n, power, seed)
    return c.join(patterns.select("pattern", F.lit(True).alias("ok")), "pattern", "left").select("candidate", "pattern", F.coalesce("ok", F.lit(False)).alias("accepted"))


def acceptance_rate(candidates: DataFrame) -> DataFrame:
    return candidates.agg(F.count("*").alias("candidates"), F.count_if("accepted").alias("accepted"), F.round(F.avg(F.col("accepted").cast("double")), 9).alias("rate"))


def acceptance_exact(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """The exact acceptance of the two-step sampler of power 1."""
    every = tx.agg(F.sum(two_to(F.size("items")) - 1).alias("every"))
    return patterns.agg(F.sum("freq").alias("valid")).crossJoin(every).select("valid", "every", F.round(F.col("valid") / F.col("every"), 9).alias("rate"))


def scan_stored(patterns: DataFrame, path: str, batches: int, size: int = 50, seed: int = SAMPLE_SEED) -> DataFrame:
    """scan_sample with the miner's output written to disk once and read for each draw, instead of mined anew."""
    patterns.select("pattern", "items").write.parquet(path)
    return scan_sample(patterns.sparkSession.read.parquet(path), batches, size, seed)


def scan_sample(patterns: DataFrame, batches: int, size: int = 50, seed: int = SAMPLE_SEED) -> DataFrame:
    """(batch, pos, line, pattern, items): line numbers of the miner's output are drawn, and printed as they are met in the next scan, which is why
    positions of a batch aren't exchangeable (B7).  The search order is that of the patterns' texts."""
    spark = patterns.sparkSession
    keyed = patterns.select("pattern", "items").withColumn("part", F.substring("pattern", 1, 6))
    parts = keyed.groupBy("part").agg(F.count("*").alias("n")).withColumn("base", F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n"))
    numbered = keyed.withColumn("line", F.row_number().over(Window.partitionBy("part").orderBy("pattern"))).join(parts, "part").select((F.col("line") + F.col("base") - 1).alias("line"), "pattern", "items")
    total = patterns.agg(F.count("*").alias("total"))
    drawn = ids(spark, batches, "batch").crossJoin(ids(spark, size, "k")).crossJoin(total).select("batch", "k", share_of(draw(F.lit(seed), F.lit("scan"), F.col("batch"), F.col("k")), F.col("total")).alias("line"))
    drawn = drawn.withColumn("pos", F.row_number().over(Window.partitionBy("batch").orderBy("line", "k")))
    return drawn.join(numbered, "line").select("batch", "pos", "line", "pattern", "items")


def batches_of(samples: DataFrame, size: int = 50) -> DataFrame:
    """(batch, pos, pattern, items) of the accepted samples in the order of their numbers, by blocks of sample numbers."""
    ok = samples.where("pattern is not null")
    return ok.select(F.floor(F.col("sample_id") / size).alias("batch"), (F.col("sample_id") % size + 1).cast("int").alias("pos"), "pattern", F.split("pattern", ",").alias("items"))


class Chain(Search):
    """States are masks over spec.Data; each chain is one row with its own seed.

    A chain walks over a space that holds the task's patterns and may be larger.  It is looked at after the burn-in and then after each gap; a state that isn't a
    pattern of the task, or has no weight, is passed over and the chain looked at again a gap later, so the samples follow the chain's law on the patterns.  Looking
    again at the very next pattern instead would favour those next to the rest of the space."""

    start = 0

    def cover(self, mask: int) -> int:
        cover = self.data.everything
        for j in range(mask.bit_length()):
            if mask >> j & 1:
                cover &= self.data.bitmaps[j]
        return cover

    def weight(self, mask: int) -> int:
        cover = self.cover(mask)
        return self.q.weight(mask.bit_count(), self.data.count(cover), self.data.count_pos(cover))

    def step(self, mask: int, rng: random.Random) -> int:
        raise NotImplementedError

    def sampled(self, mask: int) -> bool:
        return bool(mask or self.c.allow_empty) and self.valid(mask, self.cover(mask))

    def run(self, rng: random.Random, burn_in: int, gap: int, n: int, max_gaps: int) -> Iterator[int]:
        """At most n samples; fewer where max_gaps looks in a row find no pattern."""
        mask, left, missed = self.start, burn_in, 0
        while n and missed < max_gaps:
            mask = self.step(mask, rng)
            left -= 1
            if left <= 0:
                left = gap
                if self.sampled(mask):
                    yield mask
                    n, missed = n - 1, 0
                else:
                    missed += 1


class FlipChain(Chain):
    """A random frequent item is toggled; the move is made if the set stays frequent.  Uniform over frequent sets, the empty one among them."""

    def step(self, mask: int, rng: random.Random) -> int:
        new = mask ^ 1 << rng.choice(self.frequent)
        return new if new < mask and new & mask == new or self.data.count(self.cover(new)) >= self.c.minsup else mask


class Metropolis(Chain):
    """Steps between neighbours, accepted by the ratio of weights and of the ways there and back; states without weight count 1, so that they connect the rest."""

    def __init__(self, *args) -> None:
        super().__init__(*args)
        self.known: dict[int, tuple[list[int], int]] = {}

    def neighbours(self, mask: int) -> list[int]:
        raise NotImplementedError

    def of(self, mask: int) -> tuple[list[int], int]:
        if mask not in self.known:
            if len(self.known) > 200_000:
                self.known.clear()
            self.known[mask] = (self.neighbours(mask), max(1, self.weight(mask)))
        return self.known[mask]

    def sampled(self, mask: int) -> bool:
        return super().sampled(mask) and self.weight(mask) > 0

    def step(self, mask: int, rng: random.Random) -> int:
        ways, w = self.of(mask)
        new = rng.choice(ways)
        back, w2 = self.of(new)
        there, here = ways.count(new), back.count(mask)
        # each way is as likely as any other of its state
        return new if new != mask and rng.random() * w * there * len(back) < w2 * here * len(ways) else mask


class LatticeWalk(Metropolis):
    """Between frequent sets that differ by one item, by any quality and under any constraint."""

    def neighbours(self, mask: int) -> list[int]:
        out, cover = [], self.cover(mask)
        for j in self.frequent:
            if mask >> j & 1:
                out.append(mask ^ 1 << j)
            elif self.data.count(cover & self.data.bitmaps[j]) >= self.c.minsup and (self.c.max_len is None or mask.bit_count() < self.c.max_len):
                out.append(mask | 1 << j)
        return out


class ConceptWalk(Metropolis):
    """Over closed sets: up by adding an item and closing, down by dropping an item and closing what is left.

    All moves of a state are counted, so the acceptance ratio is exact; a move that leads back to the state itself keeps it."""

    def __init__(self, *args) -> None:
        super().__init__(*args)
        self.start = self.closure(self.data.everything)

    def closure(self, cover: int) -> int:
        return sum(1 << j for j, b in enumerate(self.data.bitmaps) if cover & b == cover)

    def neighbours(self, mask: int) -> list[int]:
        cover, out = self.cover(mask), []
        for j in self.frequent:
            if not mask >> j & 1:
                up = cover & self.data.bitmaps[j]
                out.append(self.closure(up) if self.data.count(up) >= self.c.minsup else mask)
            else:
                out.append(self.closure(self.cover(mask ^ 1 << j)))
        return out

    def sampled(self, mask: int) -> bool:
        cover = self.cover(mask)  # states are closed already
        return bool(mask or self.c.allow_empty) and self.admissible(mask, self.data.count(cover), self.data.count_pos(cover)) and self.weight(mask) > 0


CHAINS = {"flip": FlipChain, "lattice": LatticeWalk, "concept": ConceptWalk}


def chain_sample(spark: SparkSession, data: Data, task: MiningTask, kind: str, n: int, burn_in: int = 100_000, gap: int | None = None, chains: int = 8, seed: int = SAMPLE_SEED, max_gaps: int = 10_000) -> DataFrame:
    """(sample_id, chain, pattern): `chains` independent chains, one row each, every one with its own burn-in.  The gap between samples is by
    default items * ln(items) (B4a)."""
    held = spark.sparkContext.broadcast(data)

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        walk = CHAINS[kind](held.value, task.constraints, task.quality)
        k = len(walk.frequent)
        between = gap if gap is not None else max(1, round(k * math.log(max(2, k))))
        for b in batches:
            for c in b["id"]:
                want = n // chains + (1 if c < n % chains else 0)
                if want and k:
                    got = list(walk.run(random.Random(f"{seed}:{c}"), burn_in, between, want, max_gaps))
                    if not got:
                        continue
                    yield pd.DataFrame({"sample_id": [int(c) + chains * i for i in range(len(got))], "chain": int(c), "pattern": [walk.names(m) for m in got]})

    return spark.range(0, chains, 1, chains).mapInPandas(work, "sample_id bigint, chain bigint, pattern string")


def capabilities(spark: SparkSession) -> DataFrame:
    """What each kind of sampler offers (Table 1)."""
    rows = [
        ("flip chain", "minimal", "no", "no", "yes", "no"),
        ("lattice walk", "yes", "yes", "no", "depends", "no"),
        ("concept walk", "monotone", "yes", "no", "yes", "no"),
        ("two-step", "no", "no", "yes", "yes", "no"),
        ("cell sampler", "generic oracle", "yes", "yes", "tidset oracle", "yes"),
    ]
    return spark.createDataFrame(rows, "sampler string, constraints string, distributions string, guarantees string, efficiency string, pattern_sets string")
