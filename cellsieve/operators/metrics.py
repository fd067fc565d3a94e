"""Accuracy measures (A1-A15) over tables of patterns and samples."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def empirical(samples: DataFrame) -> DataFrame:
    """(pattern, n, p_empirical) of the samples that have a pattern (A2)."""
    n = samples.where("pattern is not null").groupBy("pattern").agg(F.count("*").alias("n"))
    return n.crossJoin(F.broadcast(n.agg(F.sum("n").alias("all")))).select("pattern", "n", (F.col("n") / F.col("all")).alias("p_empirical"))


def compared(target: DataFrame, samples: DataFrame) -> DataFrame:
    """(pattern, p, q): target and empirical probability, 0 where a side lacks the pattern; one full outer join."""
    return target.join(empirical(samples), "pattern", "full").select("pattern", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("p_empirical", F.lit(0.0)).alias("q"))


def _term(a, b):
    return F.when(a > 0, a * F.log2(a / b)).otherwise(F.lit(0.0))


def kl_divergence(pq: DataFrame) -> DataFrame:
    """Of the empirical distribution from the target, in bits; infinite where a sampled pattern has no target probability (A3)."""
    return pq.agg(F.round(F.sum(F.when((F.col("q") > 0) & (F.col("p") == 0), F.lit(float("inf"))).otherwise(_term(F.col("q"), F.col("p")))), 9).alias("kl"))


def js_divergence(pq: DataFrame) -> DataFrame:
    """Mean divergence from the midpoint, 0 to 1 (A4)."""
    m = (F.col("p") + F.col("q")) / 2
    return pq.agg(F.round(F.sum(_term(F.col("p"), m) + _term(F.col("q"), m)) / 2, 9).alias("js"))


def js_divergences(targets: DataFrame, samples: DataFrame) -> DataFrame:
    """(ask, js): js_divergence of many sets of samples, (ask, pattern), from the targets (ask, pattern, p) of their own, in one job."""
    n = samples.where("pattern is not null").groupBy("ask", "pattern").agg(F.count("*").alias("n"))
    q = n.join(n.groupBy("ask").agg(F.sum("n").alias("all")), "ask").select("ask", "pattern", (F.col("n") / F.col("all")).alias("q"))
    pq = targets.join(q, ["ask", "pattern"], "full").select("ask", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q"))
    m = (F.col("p") + F.col("q")) / 2
    return pq.groupBy("ask").agg(F.round(F.sum(_term(F.col("p"), m) + _term(F.col("q"), m)) / 2, 9).alias("js"))


def js_gap(target: DataFrame, ours: DataFrame, ideal: DataFrame) -> DataFrame:
    """One row: divergence of our samples and of as many ideal ones from the target, and their difference (A5)."""
    a, b = js_divergence(compared(target, ours)).select(F.col("js").alias("ours")), js_divergence(compared(target, ideal)).select(F.col("js").alias("ideal"))
    return a.crossJoin(b).withColumn("gap", F.round(F.col("ours") - F.col("ideal"), 9))


def js_expected(patterns: int, samples: int) -> float:
    """What an exact sampler can be expected to reach."""
    return (patterns - 1) / (8 * samples * math.log(2))


def share_within_factor(pq: DataFrame, factor: float = 2.0) -> DataFrame:
    """Share of target patterns whose empirical probability is within the factor of it."""
    inside = (F.col("q") * factor >= F.col("p")) & (F.col("q") <= F.col("p") * factor)
    return pq.where("p > 0").agg(F.round(F.avg(inside.cast("double")), 9).alias("share"))


def check_guarantee(pq: DataFrame, epsilon: float, samples: int, least_expected: int = 20) -> DataFrame:
    """Patterns that are expected often enough to judge, and how many lie outside the factor 1 + epsilon."""
    outside = ~((F.col("q") * (1 + epsilon) >= F.col("p")) & (F.col("q") <= F.col("p") * (1 + epsilon)))
    return pq.where(F.col("p") * samples >= least_expected).agg(F.count("*").alias("judged"), F.count_if(outside).alias("outside"))


def band_by_target(patterns: DataFrame, pq: DataFrame, value: str = "freq") -> DataFrame:
    """Per level of the quality: target, mean, 5 % and 95 % of the empirical probability."""
    return patterns.join(pq, "pattern").groupBy(value).agg(
        F.count("*").alias("n"), F.round(F.avg("p"), 12).alias("target"), F.round(F.avg("q"), 12).alias("mean"),
        F.round(F.expr("percentile(q, 0.05)"), 12).alias("low"), F.round(F.expr("percentile(q, 0.95)"), 12).alias("high"),
    )


def estimate_trace(runs: DataFrame) -> DataFrame:
    """(run, estimate, running_median) in the order of runs."""
    w = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, 0)
    return runs.select("run", "estimate", F.expr("percentile(estimate, 0.5)").over(w).alias("running_median"))


def success_rate(samples: DataFrame) -> DataFrame:
    """(status, n, share)."""
    n = samples.groupBy("status").agg(F.count("*").alias("n"))
    return n.crossJoin(n.agg(F.sum("n").alias("all"))).select("status", "n", F.round(F.col("n") / F.col("all"), 9).alias("share"))


def exchangeability(samples: DataFrame) -> DataFrame:
    """(item, pos, share): share of batches whose sample at the position holds the item; samples have batch, pos, items."""
    batches = samples.agg(F.countDistinct("batch").alias("batches"))
    return samples.select("batch", "pos", F.explode("items").alias("item")).groupBy("item", "pos").agg(F.count("*").alias("n")).crossJoin(batches).select("item", "pos", F.round(F.col("n") / F.col("batches"), 9).alias("share"))


def exchangeability_gap(samples: DataFrame, positions: int, parts: int = 5) -> DataFrame:
    """One row: the largest range, over items, of an item's share among the parts of a batch.  0 for exchangeable samples, but for noise."""
    part = F.floor((F.col("pos") - 1) * parts / positions)
    n = samples.groupBy(part.alias("part")).agg(F.count("*").alias("all"))
    items = samples.select(F.explode("items").alias("item")).distinct().crossJoin(n)
    held = samples.select(part.alias("part"), F.explode("items").alias("item")).groupBy("part", "item").agg(F.count("*").alias("n"))
    share = items.join(held, ["part", "item"], "left").withColumn("share", F.coalesce("n", F.lit(0)) / F.col("all"))
    return share.groupBy("item").agg((F.max("share") - F.min("share")).alias("gap")).agg(F.round(F.max("gap"), 9).alias("largest_gap"), F.round(F.avg("gap"), 9).alias("mean_gap"))


def value_percentiles(everything: DataFrame, value: str) -> DataFrame:
    """min, 1, 25, 50, 75, 99 % and max of a value over all patterns or sets."""
    cuts = {"p01": 0.01, "p25": 0.25, "p50": 0.5, "p75": 0.75, "p99": 0.99}
    return everything.agg(F.count("*").alias("n"), F.min(value).alias("least"), *[F.expr(f"round(percentile({value}, {q}), 6)").alias(n) for n, q in cuts.items()], F.max(value).alias("most"))


def value_ranks(everything: DataFrame, samples: DataFrame, value: str) -> DataFrame:
    """samples with the share of all patterns or sets whose value is smaller, by one join with the table of distinct values."""
    per = everything.groupBy(value).agg(F.count("*").alias("n"))
    below = per.select(value, F.coalesce(F.sum("n").over(Window.orderBy(value).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("below"))
    total = per.agg(F.sum("n").alias("all"))
    return samples.join(below, value).crossJoin(F.broadcast(total)).withColumn("rank", F.round(F.col("below") / F.col("all"), 9)).drop("below", "all")


def diversity(samples: DataFrame) -> DataFrame:
    """One row: samples, share of distinct ones, items touched, mean Jaccard of pairs of samples.

    The mean over pairs comes from counts: distinct patterns are paired, weighted by how often they were drawn."""
    n = samples.groupBy("pattern", "items").agg(F.count("*").alias("n"))
    a, b = n.select(F.col("items").alias("ia"), F.col("n").alias("na"), F.col("pattern").alias("pa")), n.select(F.col("items").alias("ib"), F.col("n").alias("nb"), F.col("pattern").alias("pb"))
    both = F.size(F.array_intersect("ia", "ib"))
    pairs = F.when(F.col("pa") == F.col("pb"), F.col("na") * (F.col("na") - 1)).otherwise(F.col("na") * F.col("nb"))
    jac = a.crossJoin(b).agg((F.sum(pairs * both / (F.size("ia") + F.size("ib") - both)) / F.sum(pairs)).alias("j"))
    touched = samples.select(F.explode("items").alias("i")).agg(F.countDistinct("i").alias("items_touched"))
    return n.agg(F.sum("n").alias("samples"), F.round(F.count("*") / F.sum("n"), 9).alias("distinct_share")).crossJoin(touched).crossJoin(jac.select(F.round("j", 9).alias("mean_jaccard")))
