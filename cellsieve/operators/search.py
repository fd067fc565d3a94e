"""Estimation and sampling with search oracles (M7, M10, M12-M16, M18): one row of a DataFrame for each run or sample, searched in Python workers.

The condensed, vertical data goes to the workers by broadcast, after a check of its size; plans.planner chooses another oracle beyond it.
Runs and samples are independent by construction, so the work is spread by repartitioning their numbers; every seed comes from
(seed, number), so results do not depend on the partitioning.
"""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession

from ..functions.hashing import draw_py
from ..functions.lineage import cut
from ..params import EstimateParams, cell_range, initial_xors
from ..spec import Data, MiningTask
from . import blocks
from .cells import ESTIMATE_SEED, SAMPLE_SEED
from .oracles import ORACLES, Search, xor_rows

#: Cells of condensed bitmaps that may be broadcast, in bytes.
BROADCAST_BYTES = 1 << 30


def collect_data(tx: DataFrame, minsup: int | None = None, limit_bytes: int = BROADCAST_BYTES) -> Data:
    """Condensed transactions for the search oracles; raises where they exceed the limit, before any row is gathered."""
    return collect_blocks(blocks.coded(tx), minsup, limit_bytes)


def collect_blocks(coded: DataFrame, minsup: int | None = None, limit_bytes: int = BROADCAST_BYTES) -> Data:
    """The same from blocks.coded.  Items below minsup go; transactions that become empty stay, since they count.  What the driver gathers is a row's codes, some
    bytes, and then a bit for each row and item."""
    from pyspark.sql import functions as F

    items = blocks.item_counts(coded).where(F.col("freq") >= max(1, minsup or 1)).select("item", "freq").orderBy("freq", "item").toArrow()
    names = items.column("item").to_pylist()
    rows = cut(blocks.condensed(coded, {name: j for j, name in enumerate(names)}))
    n, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.length("row")), F.lit(0))).first()
    if n * (len(names) / 8 + 24) + size > limit_bytes:
        raise ValueError("the condensed data is too large to be broadcast; use the relational or the sharded oracle")
    return Data(names, *blocks.gathered(rows, names))


@dataclass
class Estimate:
    """total is the median of the runs' estimates, in integer weights."""

    total: float
    runs: list[dict]
    w_min: float

    @property
    def calls(self) -> int:
        return sum(r["calls"] for r in self.runs)


def one_estimate(oracle: Search, quality_scale: float, w_max: float, pivot: float, run: int, attempts: int, seed: int, start: int) -> dict:
    """One run: constraints are added until the cell weighs no more than the pivot; an empty cell starts anew with other constraints."""
    bound, calls, least = pivot * quality_scale * w_max, 0, math.inf
    for attempt in range(attempts):
        m = start
        while m <= len(oracle.data.items):
            rows = xor_rows(oracle.data, seed, run * attempts + attempt, m)
            cell = oracle.solve(rows, bound)
            calls += 1
            least = min(least, min((s[3] for s in cell.solutions), default=math.inf))
            if not cell.overflow:
                break
            m += 1
        if not cell.overflow and cell.weight:
            return {"run": run, "m": m, "cell_weight": float(cell.weight), "attempt": attempt, "estimate": float(cell.weight) * 2**m, "calls": calls, "w_min": float(least)}
    return {"run": run, "m": -1, "cell_weight": 0.0, "attempt": attempts, "estimate": math.nan, "calls": calls, "w_min": float(least)}


def one_sample(oracle: Search, scale: float, w_max: float, kappa: float, total: float, sample: int, seed: int, schedule: str) -> dict:
    """One sample (M10, M15).  "theory" starts at N and adds up to three constraints; "leapfrog" starts at N + 1, drops one when the cell is too light, or adds up to two."""
    lo, hi = (x * scale * w_max for x in cell_range(kappa))
    n, calls = initial_xors(total / scale, kappa, w_max), 0

    def cell(m: int):
        nonlocal calls
        calls += 1
        return oracle.solve(xor_rows(oracle.data, seed, sample, m), hi)

    levels = [n, n + 1, n + 2, n + 3]
    if schedule == "leapfrog" and n > 0:
        m, got = n + 1, cell(n + 1)
        if not got.overflow and got.weight < lo:
            m, got = n, cell(n)
        else:
            while got.overflow and m < n + 3:
                m += 1
                got = cell(m)
    else:
        for m in levels:
            got = cell(m)
            if not got.overflow:
                break
    if got.overflow:
        status, pick = "too_large", None
    elif got.weight == 0 or got.weight < lo and m > 0:
        status, pick = "too_small", None
    else:
        status = "ok"
        pick = max((math.log((draw_py(seed, "pick", sample, oracle.names(s[0])) + 0.5) / 2.0**52) / s[3], oracle.names(s[0]), s) for s in got.solutions)
    return {
        "sample_id": sample, "status": status, "pattern": pick[1] if pick else None, "freq": pick[2][1] if pick else None, "w": float(pick[2][3]) if pick else None,
        "n_xor": m, "cell_weight": float(got.weight), "cell_size": len(got.solutions), "oracle_calls": calls,
    }


RUN_SCHEMA = "run bigint, m int, cell_weight double, attempt int, estimate double, calls int, w_min double"
SAMPLE_SCHEMA = "sample_id bigint, status string, pattern string, freq bigint, w double, n_xor int, cell_weight double, cell_size int, oracle_calls int"


@dataclass
class Sampler:
    """Estimates, and samples from, the space of one task."""

    spark: SparkSession
    data: Data
    task: MiningTask
    oracle: str = "tidset"
    tasks: int = 64
    held: Broadcast | None = None

    def __post_init__(self) -> None:
        self.held = self.held or self.spark.sparkContext.broadcast(self.data)
        stats, c = self.data.stats(), self.task.constraints.bound(self.data.transactions)
        self.scale = float(self.task.quality.scale(stats))
        self.tilt = float(self.task.quality.tilt(stats, c))
        self.w_max = 1.0

    def spread(self, start: int, stop: int) -> DataFrame:
        return self.spark.range(start, stop, 1, max(1, min(self.tasks, stop - start)))

    def estimate(self, params: EstimateParams = EstimateParams(), seed: int = ESTIMATE_SEED) -> Estimate:
        """Waves of runs: three from no constraint, then, by leapfrog, the rest from the least count found so far (M14); with stop="converged" a wave is
        the last once the sampling count by the running median stays what it was (M16).  When a smaller weight than before turns up, bounds shrink for
        the later waves (M12)."""
        runs: list[dict] = []
        leap = params.schedule == "leapfrog"
        sizes = [3] if leap else []
        while sum(sizes) < params.runs:
            sizes.append(min(3 if params.stop == "converged" else params.runs, params.runs - sum(sizes)))
        w_min, derived = math.inf, None
        for size in sizes:
            start = min((r["m"] for r in runs if r["m"] >= 0), default=0) if leap else 0
            held, task, name, scale, w_max, at = self.held, self.task, self.oracle, self.scale, self.w_max, len(runs)

            def work(batches: Iterator[pd.DataFrame], start=start, w_max=w_max) -> Iterator[pd.DataFrame]:
                o = ORACLES[name](held.value, task.constraints, task.quality)
                for b in batches:
                    yield pd.DataFrame([one_estimate(o, scale, w_max, params.pivot, int(i), params.attempts, seed, start) for i in b["id"]])

            runs += [r.asDict() for r in self.spread(at, at + size).mapInPandas(work, RUN_SCHEMA).collect()]
            runs.sort(key=lambda r: r["run"])
            w_min = min(w_min, min(r["w_min"] for r in runs))
            self.w_max = min(self.w_max, w_min / self.scale * self.tilt) if math.isfinite(w_min) else self.w_max
            good = [r["estimate"] for r in runs if r["m"] >= 0]
            if good and params.stop == "converged":
                now = initial_xors(statistics.median(good) / self.scale, self.task.kappa, self.w_max)
                if now == derived:
                    break
                derived = now
        good = [r["estimate"] for r in runs if r["m"] >= 0]
        return Estimate(statistics.median(good) if good else 0.0, runs, w_min)

    def sample(self, total: float, n: int, first: int = 0, schedule: str = "leapfrog", seed: int = SAMPLE_SEED) -> DataFrame:
        """SAMPLE_SCHEMA rows for the samples first .. first + n - 1, failures among them."""
        held, task, name, scale, w_max = self.held, self.task, self.oracle, self.scale, self.w_max

        def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            o = ORACLES[name](held.value, task.constraints, task.quality)
            for b in batches:
                yield pd.DataFrame([one_sample(o, scale, w_max, task.kappa, total, int(i), seed, schedule) for i in b["id"]]).astype({"freq": "Int64"})

        return self.spread(first, first + n).mapInPandas(work, SAMPLE_SCHEMA)

    def iter_samples(self, total: float, batch: int = 50) -> Iterator[DataFrame]:
        """Batches of samples without end."""
        first = 0
        while True:
            yield self.sample(total, batch, first)
            first += batch

    def count(self) -> dict:
        """Everything, without constraints and bound: patterns, weight, nodes (B9, C9).  A task for each first item; only sums come back."""
        held, task, name = self.held, self.task, self.oracle
        first = ORACLES[name](self.data, task.constraints, task.quality).frequent

        def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            o = ORACLES[name](held.value, task.constraints, task.quality)
            for b in batches:
                for j in b["id"]:
                    got = o.branch(first[int(j)])
                    yield pd.DataFrame([(got.solutions[0][3] if got.solutions else 0, str(got.weight), got.nodes)], columns=["patterns", "weight", "nodes"])

        rows = self.spark.range(0, len(first), 1, max(1, len(first))).mapInPandas(work, "patterns bigint, weight string, nodes bigint").collect()
        return {k: sum(int(r[k]) for r in rows) for k in ("patterns", "weight", "nodes")}

    def timeline(self, kappas: tuple[float, ...] = (0.9, 0.5, 0.1), batches: int = 2, size: int = 50, params: EstimateParams = EstimateParams(), max_seconds: float = math.inf) -> list[tuple]:
        """(kappa, batch, requested, drawn, ready_s, ms_per_sample, calls): pre-processing as batch 0, then batches of samples, and when each was ready (C2-C5).  Nothing
        is started once max_seconds have passed."""
        began, out = time.perf_counter(), []
        estimate = self.estimate(params)
        seconds = lambda: round(time.perf_counter() - began, 3)
        out.append((None, 0, 0, 0, seconds(), 0.0, estimate.calls))
        for kappa in kappas:
            one = Sampler(self.spark, self.data, MiningTask(self.task.constraints, self.task.quality, kappa), self.oracle, self.tasks, self.held)
            one.w_max = self.w_max
            for b in range(batches):
                if seconds() > max_seconds or not estimate.total:
                    return out
                at = seconds()
                rows = one.sample(estimate.total, size, b * size).select("status", "oracle_calls").collect()
                out.append((kappa, b + 1, size, sum(r["status"] == "ok" for r in rows), seconds(), round((seconds() - at) * 1000 / size, 2), sum(r["oracle_calls"] for r in rows)))
        return out
