"""Functions for SQL users: Column functions, a pandas UDF for black-box qualities, and table functions."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..params import EstimateParams
from ..spec import QUALITIES, Constraints, Data, MiningTask


def parity(mask: Column, coefficients: Column) -> Column:
    """0 or 1: the parity of an itemset's mask under coefficients (M5)."""
    return F.bit_count(mask.bitwiseAND(coefficients)) % 2


def pattern_mask(ranks: str) -> Column:
    """The mask of item ranks from 0 to 61."""
    return F.aggregate(ranks, F.lit(0).cast("bigint"), lambda acc, i: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i)))


def jaccard(a: str, b: str) -> Column:
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def black_box_quality(fn: Callable[[int, int, int], int]):
    """A Column function (size, freq, freq_pos) -> bigint of any Python function (Q8)."""

    @F.pandas_udf("bigint")
    def run(size: pd.Series, freq: pd.Series, pos: pd.Series) -> pd.Series:
        return pd.Series([int(fn(int(n), int(f), int(p))) for n, f, p in zip(size, freq, pos)], dtype="int64")

    return run


class _Collector:
    """Gathers a table argument's rows (one column of items, comma-joined) of its partition and samples at its end."""

    def __init__(self) -> None:
        self.rows: dict[tuple[str, ...], int] = {}
        self.args = (0.1, 0.9, 10, "uniform")

    def eval(self, row, theta: float, kappa: float, n: int, quality: str) -> None:
        key = tuple(x for x in (row[0] or "").split(",") if x)
        self.rows[key] = self.rows.get(key, 0) + 1
        self.args = (float(theta), float(kappa), int(n), quality)

    def solved(self):
        from ..operators.oracles import TidsetOracle
        from ..operators.search import one_estimate

        theta, kappa, n, quality = self.args
        data = Data.of([(k, m, 0) for k, m in self.rows.items()])
        task = MiningTask(Constraints(theta=theta), QUALITIES[quality], kappa)
        oracle, scale, p = TidsetOracle(data, task.constraints, task.quality), float(task.quality.scale(data.stats())), EstimateParams()
        runs = [one_estimate(oracle, scale, 1.0, p.pivot, i, p.attempts, 1, 0) for i in range(p.runs)]
        good = sorted(r["estimate"] for r in runs if r["m"] >= 0)
        return oracle, scale, kappa, n, good[len(good) // 2] if good else 0.0


@udtf(returnType="sample_id bigint, status string, pattern string")
class SamplePatterns(_Collector):
    """sample_patterns(TABLE(t) WITH SINGLE PARTITION, theta, kappa, n, quality)."""

    def terminate(self) -> Iterator[tuple]:
        from ..operators.search import one_sample

        if self.rows:
            oracle, scale, kappa, n, total = self.solved()
            for k in range(n):
                got = one_sample(oracle, scale, 1.0, kappa, total, k, 2, "leapfrog")
                yield k, got["status"], got["pattern"]


@udtf(returnType="total double")
class EstimatePatterns(_Collector):
    """estimate_patterns(TABLE(t) WITH SINGLE PARTITION, theta, kappa, n, quality); kappa and n play no part."""

    def terminate(self) -> Iterator[tuple]:
        if self.rows:
            yield (self.solved()[4],)


def register(spark: SparkSession) -> None:
    spark.udtf.register("sample_patterns", SamplePatterns)
    spark.udtf.register("estimate_patterns", EstimatePatterns)
