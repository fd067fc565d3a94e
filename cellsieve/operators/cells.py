"""The relational cell sampler (M1-M17): patterns in a table, all cells of all runs from one pass over it.

An item has one 52-bit word for each run; bit k of the XOR of a pattern's words is its parity under the run's k-th random constraint.  The XOR
with the run's own word of right sides marks the constraints that the pattern breaks, and the number of trailing zeros is its depth: the count of leading
constraints that it meets.  The cell of m constraints holds the patterns of depth m or more, so one aggregation by (run, depth) and one running
sum over falling depth give every cell of every run.

Patterns times runs is the whole work, so it is done on Arrow batches of patterns, blocks of runs at a time: a pair costs a few nanoseconds, and the
product never leaves the worker.  Estimation sends on sums by run and depth, sampling the members of the first cell that it may need.  A worker
makes the words of the items that it meets from their names; it holds WORDS_HELD of them at most, whatever the number of items and runs.

Weights are integer numerators of the qualities (spec.QUALITIES), so that sums are exact; bounds are multiplied by the scale C instead.  A sum beyond the
range of its type raises.  Patterns with weight 0 are outside the space that is sampled.
"""

from __future__ import annotations

import functools
import hashlib
import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import draw, draw_py, share_of
from ..params import EstimateParams, cell_range, initial_xors
from ..spec import QUALITIES, Quality

ESTIMATE_SEED = 1
SAMPLE_SEED = 2
#: Constraints of a run.
DEEPEST = 52
#: Patterns and runs that a worker multiplies at once, and words that it holds.
PATTERN_BLOCK, RUN_BLOCK, WORDS_HELD = 2_048, 256, 1 << 24
#: Patterns that every worker may hold, so that the work of sample_many is split by runs; pairs of a pattern and a run that it looks at at once.
PATTERNS_HELD, PAIRS_HELD = 1 << 17, 1 << 19


def weighted(patterns: DataFrame, quality: Quality | str) -> DataFrame:
    """patterns with w, the integer weight; those of weight 0 go."""
    q = QUALITIES[quality] if isinstance(quality, str) else quality
    return patterns.withColumn("w", F.expr(q.spark).cast("decimal(38,0)" if q.wide else "bigint")).where("w > 0")


def target_distribution(patterns: DataFrame, quality: Quality | str) -> DataFrame:
    """(pattern, p): quality over its sum (M1)."""
    w = weighted(patterns, quality)
    return w.crossJoin(F.broadcast(w.agg(F.sum("w").alias("total")))).select("pattern", (F.col("w").cast("double") / F.col("total").cast("double")).alias("p"))


def observed_tilt(patterns: DataFrame, quality: Quality | str) -> DataFrame:
    """One row: least and largest weight and their ratio (M3)."""
    return weighted(patterns, quality).agg(F.min("w").alias("w_min"), F.max("w").alias("w_max"), F.round(F.max("w") / F.min("w"), 6).alias("tilt"))


def runs_table(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("run"))


class Words:
    """The words of items in the runs 0 .. n - 1, and the runs' right sides."""

    def __init__(self, seed: int, n: int) -> None:
        self.seed, self.n, self.held = seed, n, {}

    def block(self, start: int, names: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(words of the names by runs start .. start + RUN_BLOCK - 1, a row of zeros last; right sides)."""
        runs = range(start, min(self.n, start + RUN_BLOCK))
        if len(self.held) * RUN_BLOCK > WORDS_HELD:
            self.held.clear()
        for i in (*names, "parity"):
            if (start, i) not in self.held:
                self.held[start, i] = np.array([draw_py(self.seed, r, i) for r in runs], np.int64)
        return np.stack([*(self.held[start, i] for i in names), np.zeros(len(runs), np.int64)]), self.held[start, "parity"]


def crossed(batch: pa.RecordBatch, words: Words, least: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first run, runs from it, rows of the batch, depths) of the pairs whose depth is at least `least`, by blocks of runs."""
    column = batch.column("items")
    size = np.maximum(column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), 0).astype(np.int64)
    coded = column.flatten().dictionary_encode()
    names = coded.dictionary.to_pylist()
    # every pattern ends with the row of zeros, so that an empty one is a stretch too
    ends = np.cumsum(size + 1)
    codes = np.full(int(ends[-1]) if len(ends) else 0, len(names), np.int64)
    inner = np.ones(len(codes), bool)
    inner[ends - 1] = False
    codes[inner] = coded.indices.to_numpy(zero_copy_only=False)
    mask = np.int64((1 << least) - 1)
    for start in range(0, words.n, RUN_BLOCK):
        by_item, rhs = words.block(start, names)
        broken = np.bitwise_xor.reduceat(by_item[codes], ends - size - 1, axis=0) ^ rhs
        at, run = np.nonzero(broken & mask == 0)
        v = broken[at, run]
        depth = np.where(v == 0, DEEPEST, np.bitwise_count((v & -v) - 1)).astype(np.int32)
        yield start, run, at, depth


def spread(patterns: DataFrame) -> DataFrame:
    """The product is the work: a small pattern table must not end up in one partition; a number given here is kept by adaptive execution."""
    spark = patterns.sparkSession
    return patterns.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism))


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, PATTERN_BLOCK):
            yield whole.slice(at, PATTERN_BLOCK)


def with_depth(patterns: DataFrame, runs: int, seed: int, least: int = 0) -> DataFrame:
    """Every (run, pattern) with the pattern's depth in the run, where it is at least `least`; items go, the other columns stay."""
    kept = [c for c in patterns.columns if c != "items"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words(seed, runs)
        for b in slices(batches):
            slim = b.select(kept)
            for start, run, at, depth in crossed(b, words, least):
                if len(at):
                    yield pa.RecordBatch.from_arrays([*slim.take(pa.array(at)).columns, pa.array(run + start, pa.int64()), pa.array(depth, pa.int32())], [*kept, "run", "depth"])

    schema = patterns.select(kept).withColumns({"run": F.lit(0).cast("bigint"), "depth": F.lit(0)}).schema
    return spread(patterns).mapInArrow(work, schema)


def depth_sums(patterns: DataFrame, runs: int, seed: int) -> DataFrame:
    """(run, depth, w, n): weight and number of the patterns of that very depth; patterns have items and w.  Sums of a batch are made where it is multiplied."""
    kind = patterns.schema["w"].dataType.simpleString()
    wide = kind != "bigint"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import decimal

        words = Words(seed, runs)
        for b in slices(batches):
            w = np.array([int(x) for x in b.column("w").to_pylist()], object)
            # sums of a block stay inside 64 bits, or are made with Python's integers
            small = not len(w) or max(w) < (1 << 62) // PATTERN_BLOCK
            w = w.astype(np.int64) if small else w
            for start, run, at, depth in crossed(b, words, 0):
                cells = (min(words.n - start, RUN_BLOCK), DEEPEST + 1)
                weight, count = np.zeros(cells, w.dtype), np.zeros(cells, np.int64)
                np.add.at(weight, (run, depth), w[at])
                np.add.at(count, (run, depth), 1)
                r, d = np.nonzero(count)
                sums = [decimal.Decimal(int(x)) for x in weight[r, d]] if wide else weight[r, d].tolist()
                yield pa.RecordBatch.from_arrays([pa.array(r + start, pa.int64()), pa.array(d, pa.int32()), pa.array(sums, pa.decimal128(38, 0) if wide else pa.int64()), pa.array(count[r, d])], ["run", "depth", "w", "n"])

    per = spread(patterns.select("items", "w")).mapInArrow(work, f"run bigint, depth int, w {kind}, n bigint")
    return per.groupBy("run", "depth").agg(F.sum("w").cast(kind).alias("w"), F.sum("n").alias("n"))


def raced(patterns: DataFrame, runs: int, seed: int, start: int) -> DataFrame:
    """(run, level, w, key, pattern) of each batch: of the patterns with start + level constraints (3: or more), their weight and the one whose key,
    round(ln(u) / w, 12) for its own draw u, is the largest, then the last by name."""
    kind = patterns.schema["w"].dataType.simpleString()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import decimal
        import hashlib
        import math

        words, md5, log = Words(seed, runs), hashlib.md5, math.log
        for b in slices(batches):
            names, w = b.column("pattern").to_pylist(), [int(x) for x in b.column("w").to_pylist()]
            for first, run, at, depth in crossed(b, words, start):
                sums: dict[tuple[int, int], int] = {}
                best: dict[tuple[int, int], tuple[float, str]] = {}
                for r, p, level in zip((run + first).tolist(), at.tolist(), np.minimum(depth - start, 3).tolist()):
                    cell = r, level
                    u = int(md5(f"{seed}:pick:{r}:{names[p]}".encode()).hexdigest()[:13], 16)
                    key = log((u + 0.5) / 4503599627370496.0) / w[p]
                    if cell in sums:
                        sums[cell] += w[p]
                        if key > best[cell][0] - 1e-11:
                            best[cell] = max(best[cell], (round(key, 12), names[p]))
                    else:
                        sums[cell], best[cell] = w[p], (round(key, 12), names[p])
                weight = [decimal.Decimal(x) for x in sums.values()] if kind != "bigint" else list(sums.values())
                columns = [pa.array([c[0] for c in sums], pa.int64()), pa.array([c[1] for c in sums], pa.int32()), pa.array(weight, pa.int64() if kind == "bigint" else pa.decimal128(38, 0))]
                yield pa.RecordBatch.from_arrays([*columns, pa.array([k for k, _ in best.values()], pa.float64()), pa.array([n for _, n in best.values()], pa.string())], ["run", "level", "w", "key", "pattern"])

    return spread(patterns).mapInArrow(work, f"run bigint, level int, w {kind}, key double, pattern string")


def nested_cells(patterns: DataFrame, runs: int, seed: int) -> DataFrame:
    """(run, m, cell_weight, n_patterns) for every m at which some pattern has that very depth."""
    return cells_of(depth_sums(patterns, runs, seed))


def cells_of(depth: DataFrame) -> DataFrame:
    down = Window.partitionBy("run").orderBy(F.desc("depth"))
    return depth.select("run", F.col("depth").alias("m"), F.sum("w").over(down).alias("cell_weight"), F.sum("n").over(down).alias("n_patterns"))


@dataclass(frozen=True)
class Scaled:
    """Bounds in integer weights: scale C of the quality, and the rescaling by the least weight and the tilt bound."""

    scale: float
    w_max: float

    @staticmethod
    def of(scale: float, w_min: float, tilt: float) -> Scaled:
        return Scaled(scale, min(1.0, w_min / scale * tilt))


def estimate_runs(patterns: DataFrame, quality: str, scaled: Scaled, params: EstimateParams = EstimateParams(), seed: int = ESTIMATE_SEED) -> DataFrame:
    """(run, m, cell_weight, attempt, estimate) of each run (M7, M13): m is the least number of constraints whose cell weighs no more than the pivot.

    A run has `attempts` sets of constraints; the first whose cell isn't empty counts."""
    return fitting_runs(nested_cells(weighted(patterns, quality), params.runs * params.attempts, seed), params.pivot * scaled.scale * scaled.w_max, params)


def fitting_runs(cells: DataFrame, bound: float, params: EstimateParams, base: int = 0) -> DataFrame:
    """estimate_runs from the cells of all attempts with `base` constraints or more, wherever they were searched."""
    # between two listed depths the cell is that of the deeper one, so the least m is one above the last depth that is too heavy
    up = Window.partitionBy("run").orderBy(F.desc("m"))
    firsts = cells.withColumn("before", F.lead("m").over(up)).withColumn("before_weight", F.lead("cell_weight").over(up))
    fits = firsts.where((F.col("cell_weight") <= bound) & (F.col("before_weight").isNull() | (F.col("before_weight") > bound)))
    fits = fits.select("run", F.when(F.col("before").isNull(), base).otherwise(F.col("before") + 1).cast("int").alias("m"), "cell_weight")
    tried = fits.select(F.floor(F.col("run") / params.attempts).cast("bigint").alias("run"), (F.col("run") % params.attempts).cast("int").alias("attempt"), "m", "cell_weight")
    best = tried.groupBy("run").agg(F.min_by(F.struct("m", "cell_weight", "attempt"), "attempt").alias("b"))
    estimate = F.col("b.cell_weight").cast("double") * F.pow(F.lit(2.0), F.col("b.m"))
    return best.select("run", F.col("b.m").alias("m"), F.col("b.cell_weight").alias("cell_weight"), F.col("b.attempt").alias("attempt"), estimate.alias("estimate"))


def estimate_total(runs: DataFrame, patterns: DataFrame, quality: str) -> DataFrame:
    """One row: the median estimate, the true total, and the relative error."""
    true = weighted(patterns, quality).agg(F.sum("w").alias("true_total"))
    return runs.agg(F.expr("percentile(estimate, 0.5)").alias("median_estimate"), F.min("m").alias("least_xors")).crossJoin(true).withColumn("error", F.round(F.abs(F.col("median_estimate") - F.col("true_total")) / F.col("true_total"), 9))


def sample(patterns: DataFrame, quality: str, scaled: Scaled, total: float, n: int, kappa: float, seed: int = SAMPLE_SEED) -> DataFrame:
    """(sample_id, status, pattern, n_xor, cell_weight, oracle_calls), a row for each requested sample.

    Cells of N to N + 3 constraints are tried in turn: in range, one pattern is drawn by weight; too heavy, one more is added; too light, the sample
    fails as `too_small`, after the fourth cell as `too_large`.  The draw is an exponential race: the pattern with the least -ln(u) / w wins, which needs no
    cell to be gathered (A.6)."""
    start = initial_xors(total / scaled.scale, kappa, scaled.w_max)
    per = raced(weighted(patterns, quality).select("pattern", "items", "w"), n, seed, start)
    each = per.groupBy("run", "level").agg(F.sum("w").cast(per.schema["w"].dataType).alias("w"), F.max(F.struct("key", "pattern")).alias("best"))
    return drawn_cells(each, patterns.sparkSession, scaled, start, n, kappa)


def sample_many(patterns: DataFrame, asks: Sequence[tuple[str, Scaled, float, int, float]], seed: int = SAMPLE_SEED) -> DataFrame:
    """sample's rows for each of the asks (quality, scaled, total, n, kappa), with its number as `ask`.

    Depths and draws are the same for all of them, so each pair of a pattern and a run is hashed once.  A run is drawn where all patterns are, and just the drawn
    rows leave the worker; with more than PATTERNS_HELD patterns, or with weights beyond 64 bits, the asks are sampled one after the other."""
    spark, kinds = patterns.sparkSession, list(dict.fromkeys(a[0] for a in asks))
    if any(QUALITIES[q].wide for q in kinds) or patterns.count() > PATTERNS_HELD:
        parts = [sample(patterns, q, scaled, total, n, kappa, seed).withColumn("ask", F.lit(k)) for k, (q, scaled, total, n, kappa) in enumerate(asks)]
        return functools.reduce(DataFrame.unionByName, parts)
    held = patterns.select("pattern", "items", *[F.greatest(F.expr(QUALITIES[q].spark).cast("bigint"), F.lit(0).cast("bigint")).alias(q) for q in kinds]).toArrow().combine_chunks()
    names, items = held.column("pattern").to_pylist(), held.column("items").to_pylist()
    words = sorted({i for row in items for i in row})
    at = {i: k for k, i in enumerate(words)}
    # every pattern ends with the row of zeros, as in `crossed`
    codes = np.array([c for row in items for c in (*(at[i] for i in row), len(words))], np.int64)
    firsts = np.cumsum([0, *(len(row) + 1 for row in items)])[:-1]
    weights = {q: held.column(q).to_numpy() for q in kinds}
    ranges = []
    for q, scaled, total, n, kappa in asks:
        lo, hi = (x * scaled.scale * scaled.w_max for x in cell_range(kappa))
        ranges.append((weights[q], initial_xors(total / scaled.scale, kappa, scaled.w_max), n, lo, hi))

    def drawn(run: np.ndarray) -> Iterator[tuple]:
        by_item = np.array([[draw_py(seed, r, i) for r in run.tolist()] for i in words] + [[0] * len(run)], np.int64)
        broken = np.bitwise_xor.reduceat(by_item[codes], firsts, axis=0) ^ np.array([draw_py(seed, r, "parity") for r in run.tolist()], np.int64)
        depth = np.where(broken == 0, DEEPEST, np.bitwise_count((broken & -broken) - 1)).astype(np.int32)
        p, r = np.nonzero(depth >= min(x[1] for x in ranges))
        depth = depth[p, r]
        md5, heads = hashlib.md5, [f"{seed}:pick:{x}:" for x in run.tolist()]
        u = np.frombuffer(b"".join([md5((heads[b] + names[a]).encode()).digest()[:8] for a, b in zip(p.tolist(), r.tolist())]), ">u8").astype(np.int64) >> 12 & (1 << 52) - 1
        log = np.log((u + 0.5) / 4503599627370496.0)
        for ask, (w, start, n, lo, hi) in enumerate(ranges):
            inside = np.flatnonzero((w[p] > 0) & (depth >= start) & (run[r] < n))
            ip, ir, level = p[inside], r[inside], np.minimum(depth[inside] - start, 3)
            cells = np.zeros((len(run), 4), np.int64)
            np.add.at(cells, (ir, level), w[ip])
            cells = cells[:, ::-1].cumsum(axis=1)[:, ::-1]
            fits = cells <= hi
            first, found = fits.argmax(axis=1), fits.any(axis=1)
            weight = np.where(found, cells[np.arange(len(run)), first], 0)
            good = found & (weight > 0) & ((weight >= lo) | (start + first == 0))
            still = good[ir] & (level >= first[ir])
            ip, ir, drew = ip[still], ir[still], inside[still]
            key = log[drew] / w[ip]
            top = np.full(len(run), -np.inf)
            np.maximum.at(top, ir, key)
            best: dict[int, tuple[float, str]] = {}
            for k in np.flatnonzero(key > top[ir] - 1e-11).tolist():
                x = int(ir[k])
                exact = round(math.log((int(u[drew[k]]) + 0.5) / 4503599627370496.0) / int(w[ip[k]]), 12), names[ip[k]]
                best[x] = max(best.get(x, exact), exact)
            for x in np.flatnonzero(run < n).tolist():
                m = int(first[x]) if found[x] else 3
                yield ask, int(run[x]), "too_large" if not found[x] else "ok" if good[x] else "too_small", best[x][1] if good[x] else None, start + m, int(weight[x]), m + 1

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = max(1, min(RUN_BLOCK, PAIRS_HELD // max(1, len(names))))
        for b in batches:
            ids = b.column("id").to_numpy()
            for k in range(0, len(ids), block):
                rows = list(zip(*drawn(ids[k : k + block])))
                kinds = (pa.int32(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(rows, kinds)], ["ask", "sample_id", "status", "pattern", "n_xor", "cell_weight", "oracle_calls"])

    most = max((a[3] for a in asks), default=0)
    schema = "ask int, sample_id bigint, status string, pattern string, n_xor int, cell_weight bigint, oracle_calls int"
    if not names or not most:
        return spark.createDataFrame([(k, x, "too_small", None, r[1], 0, 1) for k, r in enumerate(ranges) for x in range(r[2])], schema)
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return spark.range(0, most, 1, max(1, min(tasks, most // 16))).mapInArrow(work, schema)


def drawn_cells(each: DataFrame, spark: SparkSession, scaled: Scaled, start: int, n: int, kappa: float) -> DataFrame:
    """sample's rows from (run, level, w, best): the weight of the patterns of that very level, and the winner of their race."""
    lo, hi = (x * scaled.scale * scaled.w_max for x in cell_range(kappa))
    down = Window.partitionBy("run").orderBy(F.desc("level"))
    # levels without a pattern of their very depth have the cell of the next deeper one
    every = runs_table(spark, n).crossJoin(spark.range(4).select(F.col("id").cast("int").alias("level")))
    cells = every.join(each, ["run", "level"], "left").withColumn("cell_weight", F.coalesce(F.sum("w").over(down), F.lit(0))).withColumn("best", F.max("best").over(down))
    up = Window.partitionBy("run").orderBy("level")
    if start == 0:
        # everything may be lighter than the range: with no constraint the draw is exact (the short cut of zero XORs)
        ok = (F.col("cell_weight") <= hi) & ((F.col("cell_weight") >= lo) | (F.col("level") == 0))
    else:
        ok = (F.col("cell_weight") <= hi) & (F.col("cell_weight") >= lo)
    first = cells.where(F.col("cell_weight") <= hi).withColumn("nth", F.row_number().over(up)).where("nth = 1").select("run", "level", "cell_weight", "best", (ok & (F.col("cell_weight") > 0)).alias("good"))
    out = runs_table(spark, n).join(first, "run", "left")
    status = F.when(F.col("level").isNull(), "too_large").when(F.col("good"), "ok").otherwise("too_small")
    return out.select(
        F.col("run").alias("sample_id"), status.alias("status"), F.when(F.col("good"), F.col("best.pattern")).alias("pattern"),
        (F.lit(start) + F.coalesce("level", F.lit(3))).cast("int").alias("n_xor"), F.coalesce("cell_weight", F.lit(0)).cast("bigint").alias("cell_weight"), (F.coalesce("level", F.lit(3)) + 1).cast("int").alias("oracle_calls"),
    )


def sample_tilt_sliced(patterns: DataFrame, quality: str, n: int, kappa: float, seed: int = SAMPLE_SEED) -> DataFrame:
    """(sample_id, slice, status, pattern): for high tilt (Q9).  Weights are cut at powers of two; a sample picks a slice by its weight, then a pattern inside it, where
    the tilt is at most 2."""
    w = weighted(patterns, quality).withColumn("slice", F.floor(F.log2("w")).cast("int"))
    sums = {r["slice"]: r["w"] for r in w.groupBy("slice").agg(F.sum("w").alias("w")).collect()}  # a row for each power of two: 63 at most
    total, cum, cases = sum(sums.values()), 0, []
    for s in sorted(sums):
        cum += sums[s]
        cases.append((s, cum))
    pick: Column = F.lit(cases[-1][0] if cases else 0)
    r = share_of(draw(F.lit(seed), F.lit("slice"), F.col("sample_id")), F.lit(max(1, int(total))).cast("decimal(20,0)"))
    for s, c in reversed(cases[:-1]):
        pick = F.when(r < c, F.lit(s)).otherwise(pick)
    wanted = patterns.sparkSession.range(n).select(F.col("id").alias("sample_id")).withColumn("slice", pick)
    out = None
    for s in sums:
        inside = w.where(F.col("slice") == s)
        got = sample(inside, quality, Scaled(2.0 ** (s + 1), 1.0), sums[s], n, kappa, seed + 1000 + s).select("sample_id", "status", "pattern")
        part = wanted.where(F.col("slice") == s).join(got, "sample_id")
        out = part if out is None else out.unionByName(part)
    return out if out is not None else wanted.where("false").withColumns({"status": F.lit(""), "pattern": F.lit("")})
