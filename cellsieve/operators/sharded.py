"""Oracles for data that fit no single worker: branches by first item (M24), and blocks of transactions."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.gf2 import Conflict, Gf2System
from ..functions.hashing import draw_py
from ..params import EstimateParams, cell_range, initial_xors
from ..spec import Constraints, Data, Quality
from .cells import DEEPEST, ESTIMATE_SEED, SAMPLE_SEED, Scaled, cells_of, drawn_cells, fitting_runs
from .mining import condense, item_dictionary, without_infrequent
from .oracles import CellResult, GenericOracle, Search, TidsetOracle, xor_rows


def branches(tx: DataFrame, minsup: int, whole: bool = False) -> DataFrame:
    """(branch, rank, items, mult, pos): each condensed transaction goes to the branch of each of its frequent items, with the items that come later in the
    order of rising support.  One shuffle; equal conditional transactions are added up, and only frequent items travel.  whole: with all its items, frequent or
    not, as closedness and rules on items need."""
    rows = condense(tx) if whole else condense(without_infrequent(tx, minsup))
    ranks = item_dictionary(tx).where(F.col("freq") >= minsup).select("item", "rank")
    table = F.map_from_entries(F.array_sort(F.collect_list(F.struct("item", "rank"))))
    ranked = rows.crossJoin(F.broadcast(ranks.agg(table.alias("ranks"))))
    known = F.filter(F.transform("items", lambda i: F.struct(F.element_at("ranks", i).alias("rank"), i.alias("item"))), lambda x: x["rank"].isNotNull())
    each = ranked.select("items", F.array_sort(known).alias("o"), "mult", "pos").select("items", "o", "mult", "pos", F.posexplode("o").alias("at", "first"))
    tail = F.col("items") if whole else F.transform(F.slice("o", F.col("at") + 2, F.size("o")), lambda x: x["item"])
    return each.select(F.col("first.item").alias("branch"), F.col("first.rank").alias("rank"), tail.alias("items"), "mult", "pos").groupBy("branch", "rank", "items").agg(F.sum("mult").alias("mult"), F.sum("pos").alias("pos"))


def needs_generic(c: Constraints) -> bool:
    return bool(c.closed or c.must or c.must_not or c.implies or c.one_per_attribute)


def searched_branches(tx: DataFrame, constraints: Constraints, quality: Quality, visit: Callable, schema: str, blocks: list[list[int]]) -> DataFrame:
    """visit(oracle, rows(run, m), runs) of every branch and block of runs; a branch's data is sent once to each block."""
    c = constraints.bound(tx.count()) if constraints.minsup is None else constraints
    whole = needs_generic(c)
    order: dict[str, int] = {r["item"]: r["rank"] for r in item_dictionary(tx).where(F.col("freq") >= c.minsup).select("item", "rank").collect()} if whole else {}

    def search(group: pd.DataFrame) -> pd.DataFrame:
        branch, runs = group["branch"].iloc[0], blocks[int(group["part"].iloc[0])]
        data = Data.of([(list(i), int(m), int(p)) for i, m, p in zip(group["items"], group["mult"], group["pos"])])
        if whole:
            # the branch's item is in, frequent items before it are out; closedness still sees them
            before = tuple(i for i in data.items if i in order and order[i] < order[branch])
            if branch in c.must_not or any(i in before for i in c.must):
                return visit(None, None, runs)
            oracle = GenericOracle(data, Constraints(**{**c.__dict__, "must": (*c.must, branch), "must_not": (*c.must_not, *before)}), quality)
            return visit(oracle, lambda run, m, seed: xor_rows(data, seed, run, m), runs)
        oracle = BranchOracle(data, c, quality, branch)
        return visit(oracle, lambda run, m, seed: oracle.rows(seed, run, m), runs)

    parts = F.explode(F.array(*[F.lit(k) for k in range(len(blocks))]))
    return branches(tx, c.minsup, whole).withColumn("part", parts).groupBy("branch", "part").applyInPandas(search, schema)


def in_blocks(runs: int, size: int = 256) -> list[list[int]]:
    return [list(range(a, min(runs, a + size))) for a in range(0, runs, size)] or [[]]


def sharded_cells(tx: DataFrame, constraints: Constraints, quality: Quality, cells: list[tuple[int, int]], seed: int, bound: float) -> DataFrame:
    """(run, m, weight, patterns, overflow) of each cell (run, number of constraints): branches are searched apart, each with the weight capped at the bound; a cell is
    too heavy exactly if the sum of its capped weights exceeds the bound."""

    def visit(oracle, rows, which):
        out = []
        for run, m in (cells[k] for k in which):
            if oracle is None:
                out.append((run, m, 0.0, 0, False))
                continue
            got = oracle.solve(rows(run, m, seed), bound)
            out.append((run, m, float(min(got.weight, bound + 1) if got.overflow else got.weight), len(got.solutions), got.overflow))
        return pd.DataFrame(out, columns=["run", "m", "weight", "patterns", "overflow"])

    per = searched_branches(tx, constraints, quality, visit, "run bigint, m int, weight double, patterns bigint, overflow boolean", in_blocks(len(cells)))
    return per.groupBy("run", "m").agg(F.sum("weight").alias("weight"), F.sum("patterns").alias("patterns"), (F.max("overflow") | (F.sum("weight") > bound)).alias("overflow"))


def sharded_runs(tx: DataFrame, constraints: Constraints, quality: Quality, scaled: Scaled, params: EstimateParams = EstimateParams(), seed: int = ESTIMATE_SEED) -> DataFrame:
    """estimate_runs (M7) by branches: each gives its weight by depth from the first cell that is no heavier than the pivot, and before it just that it is heavier.

    A cell that is too heavy in one branch is too heavy as a whole, so what the others know of it is not needed."""
    bound = params.pivot * scaled.scale * scaled.w_max

    def visit(oracle, rows, which):
        out = []
        for run in which if oracle is not None else ():
            m = 0
            while (got := oracle.solve(rows(run, m, seed), bound)).overflow:
                m += 1
            deep = rows(run, DEEPEST, seed)
            by: dict[int, list[int]] = {}
            for mask, _, _, w in got.solutions:
                d = next((k for k, (bits, parity) in enumerate(deep) if (bits & mask).bit_count() & 1 != parity), DEEPEST)
                t = by.setdefault(d, [0, 0])
                t[0], t[1] = t[0] + w, t[1] + 1
            out += [(run, d, w, n) for d, (w, n) in by.items()] + [(run, -1, m, 0)]
        return pd.DataFrame(out, columns=["run", "depth", "w", "n"]).astype("int64")

    per = searched_branches(tx, constraints, quality, visit, "run bigint, depth int, w bigint, n bigint", in_blocks(params.runs * params.attempts))
    known = per.where("depth < 0").groupBy("run").agg(F.max("w").cast("int").alias("known"))
    sums = per.where("depth >= 0").groupBy("run", "depth").agg(F.sum("w").alias("w"), F.sum("n").alias("n")).join(known, "run")
    # the cell before the first that all branches know is too heavy
    before = known.where("known > 0").select("run", (F.col("known") - 1).alias("depth"), F.lit(math.floor(bound) + 1).cast("bigint").alias("w"), F.lit(0).cast("bigint").alias("n"))
    return fitting_runs(cells_of(sums.where("depth >= known").drop("known").unionByName(before)), bound, params)


def sharded_sample(tx: DataFrame, constraints: Constraints, quality: Quality, scaled: Scaled, total: float, n: int, kappa: float, seed: int = SAMPLE_SEED) -> DataFrame:
    """cells.sample's rows by branches (M24): a branch gives, of each sample's cells, weight and winner of the race; the winners of the branches race on."""
    start = initial_xors(total / scaled.scale, kappa, scaled.w_max)
    hi = cell_range(kappa)[1] * scaled.scale * scaled.w_max

    def visit(oracle, rows, which):
        out = []
        for run in which if oracle is not None else ():
            for level in range(4):
                got = oracle.solve(rows(run, start + level, seed), hi)
                if not got.overflow:
                    break
                # this and with it the whole cell is too heavy
                out.append((run, level, math.floor(hi) + 1, None, None))
            if got.overflow:
                continue
            deep = rows(run, start + 3, seed)[start:]
            for mask, _, _, w in got.solutions:
                d = next((k for k, (bits, parity) in enumerate(deep) if (bits & mask).bit_count() & 1 != parity), 3)
                name = oracle.names(mask)
                out.append((run, d, w, round(math.log((draw_py(seed, "pick", run, name) + 0.5) / 2.0**52) / w, 12), name))
        best: dict[tuple[int, int], list] = {}
        for run, level, w, key, name in out:
            b = best.setdefault((run, level), [0, None, None])
            b[0] += w
            if key is not None and (b[1] is None or (key, name) > (b[1], b[2])):
                b[1], b[2] = key, name
        return pd.DataFrame([(*k, *b) for k, b in best.items()], columns=["run", "level", "w", "key", "pattern"]).astype({"run": "int64", "level": "int64", "w": "int64", "key": "float64", "pattern": "object"})

    per = searched_branches(tx, constraints, quality, visit, "run bigint, level int, w bigint, key double, pattern string", in_blocks(n))
    best = F.max(F.when(F.col("pattern").isNotNull(), F.struct("key", "pattern")))
    each = per.groupBy("run", "level").agg(F.sum("w").alias("w"), best.alias("best"))
    return drawn_cells(each, tx.sparkSession, scaled, start, n, kappa)


class BranchOracle(TidsetOracle):
    """The tidset search inside one branch: its item is fixed to 1, and counts for lengths, names and parities."""

    def __init__(self, data: Data, c: Constraints, quality: Quality, branch: str) -> None:
        inner = Constraints(**{**c.__dict__, "min_len": max(0, c.min_len - 1), "max_len": None if c.max_len is None else c.max_len - 1, "allow_empty": True})
        super().__init__(data, inner, Quality(quality.name, lambda n, f, p: quality.weight(n + 1, f, p), quality.scale, quality.tilt, quality.spark))
        self.branch = branch

    def rows(self, seed: int, run: int, m: int) -> list[tuple[int, int]]:
        words, own = [draw_py(seed, run, i) for i in self.data.items], draw_py(seed, run, self.branch)
        rhs = draw_py(seed, run, "parity") ^ own
        return [(sum((w >> k & 1) << j for j, w in enumerate(words)), rhs >> k & 1) for k in range(m)]

    def names(self, mask: int) -> str:
        return ",".join(sorted([self.branch, *(i for j, i in enumerate(self.data.items) if mask >> j & 1)]))


def block_cell(tx: DataFrame, constraints: Constraints, quality: Quality, seed: int, run: int, m: int, bound: float, frontier: int = 2_000) -> CellResult:
    """One cell with the data left in place: nodes of the search are driver-side, each round ships at most `frontier` open nodes to all partitions,
    which count the supports of the nodes and of their extensions, and only counts come back.  The bound keeps the open nodes few; the deepest are taken first.

    A node is judged when its extensions are counted, so every constraint holds, closedness too: no further item stands in all that the node covers.
    """
    c = constraints.bound(tx.count()) if constraints.minsup is None else constraints
    dictionary = [r["item"] for r in item_dictionary(tx).orderBy("rank").select("item").collect()]
    at = {n: j for j, n in enumerate(dictionary)}
    judge = Search(Data(dictionary, [0] * len(dictionary), [], []), c, quality)
    words, rhs = [draw_py(seed, run, i) for i in dictionary], draw_py(seed, run, "parity")
    out = CellResult()
    rows = condense(tx).select("items", "mult", "pos").persist()
    try:
        root = Gf2System([(sum((w >> k & 1) << j for j, w in enumerate(words)), rhs >> k & 1) for k in range(m)])
        # an open node: its items, those that may join it, its system
        open_: list[tuple[int, list[int], Gf2System]] = [(0, [j for j in range(len(dictionary))], root)]
        while open_:
            batch, open_ = open_[-frontier:], open_[:-frontier]
            found = _counted(rows, at, [mask for mask, _, _ in batch])
            for k, (mask, later, system) in enumerate(batch):
                out.nodes += 1
                counts = found.get(k, {})
                freq, pos = counts.get(-1, (0, 0))
                if freq < c.minsup:
                    continue
                live = [j for j in later if counts.get(j, (0, 0))[0] >= c.minsup]
                closed = not c.closed or all(f < freq for j, (f, _) in counts.items() if j >= 0)
                try:
                    system.assign(0, sum(1 << j for j in later if j not in set(live)))
                except Conflict:
                    continue
                if closed and judge.admissible(mask, freq, pos) and system.satisfied_by_zero():
                    w = quality.weight(mask.bit_count(), freq, pos)
                    if w > 0:
                        out.solutions.append((mask, freq, pos, w))
                        out.weight += w
                        if out.weight > bound:
                            out.overflow = True
                            return out
                if c.max_len is not None and mask.bit_count() >= c.max_len:
                    continue
                before = 0
                for i, j in enumerate(live):
                    child = system.copy()
                    try:
                        child.assign(1 << j, before)
                        open_.append((mask | 1 << j, live[i + 1 :], child))
                    except Conflict:
                        pass
                    before |= 1 << j
        return out
    except Conflict:
        return out
    finally:
        rows.unpersist()


def _counted(rows: DataFrame, at: dict[str, int], masks: list[int]) -> dict[int, dict[int, tuple[int, int]]]:
    """For each node: item -> (frequency, positive) of the node with that item besides; -1 stands for the node itself."""
    width = len(at)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        nodes = [np.array([j for j in range(width) if mask >> j & 1], np.int64) for mask in masks]
        total = np.zeros((len(masks), width + 1, 2), np.int64)
        for b in batches:
            held = np.zeros((len(b), width), bool)
            for r, items in enumerate(b["items"]):
                held[r, [at[i] for i in items]] = True
            number = b[["mult", "pos"]].to_numpy(np.int64)
            for k, node in enumerate(nodes):
                on = held[:, node].all(1)
                if on.any():
                    total[k, :width] += held[on].T.astype(np.int64) @ number[on]
                    total[k, width] += number[on].sum(0)
        for k, node in enumerate(nodes):
            total[k, node] = 0
        k, j = np.nonzero(total[:, :, 0])
        yield pd.DataFrame({"node": k, "item": np.where(j == width, -1, j), "freq": total[k, j, 0], "pos": total[k, j, 1]})

    counts = rows.mapInPandas(count, "node bigint, item bigint, freq bigint, pos bigint").groupBy("node", "item").agg(F.sum("freq").alias("freq"), F.sum("pos").alias("pos"))
    out: dict[int, dict[int, tuple[int, int]]] = {}
    for r in counts.collect():
        out.setdefault(r["node"], {})[r["item"]] = (r["freq"], r["pos"])
    return out
