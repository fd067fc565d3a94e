"""Sets of patterns (M30-M35, K11-K15): tilings and other set languages, enumerated, sampled by cells, and by search.

A pair has p1, p2 (texts), freq1, freq2, area.  Two itemsets whose covers and items don't overlap form a 2-tiling; the order of the two is fixed by the
text, so each pair is listed once (K13).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.gf2 import Conflict, Gf2System
from ..functions.hashing import draw, trailing_zeros, unit
from ..functions.lineage import cut
from ..params import EstimateParams, cell_range, initial_xors
from . import blocks
from .cells import DEEPEST, cells_of, fitting_runs, runs_table
from .oracles import Search


def sides(patterns: DataFrame) -> tuple[DataFrame, DataFrame]:
    return tuple(patterns.select(*[F.col(c).alias(f"{c}{k}") for c in ("pattern", "items", "size", "freq")]) for k in (1, 2))


def union_text(a: str = "items1", b: str = "items2") -> Column:
    return F.array_join(F.array_sort(F.array_union(a, b)), ",")


def covers(patterns: DataFrame, tx: DataFrame) -> DataFrame:
    """(row, pattern): the distinct transactions that hold each pattern, by an equi-join on items."""
    rows = tx.select(F.array_distinct("items").alias("items")).distinct().select(F.unhex(F.md5(F.array_join("items", "\x1f"))).alias("row"), F.explode("items").alias("item"))
    wanted = patterns.select("pattern", "size", F.explode("items").alias("item"))
    return rows.join(wanted, "item").groupBy("row", "pattern", "size").agg(F.count("*").alias("n")).where("n = size").select("row", "pattern")


def overlapping(patterns: DataFrame, tx: DataFrame) -> DataFrame:
    """(p1, p2), p1 < p2: pairs of patterns that some transaction holds both of (K12).  For data of any width: it needs no table of all itemsets that occur, and nothing that grows
    with the pairs that meet in each transaction."""
    return overlapping_in(patterns, blocks.coded(tx.select("items", F.lit(False).alias("label"))))


def overlapping_in(patterns: DataFrame, coded: DataFrame) -> DataFrame:
    """The same from blocks.coded; the driver and the workers hold the patterns, as numbers."""
    held = sorted((r["pattern"], r["items"]) for r in patterns.select("pattern", "items").collect())
    if not held:
        return patterns.select(F.col("pattern").alias("p1"), F.col("pattern").alias("p2")).where("false")
    names = patterns.sparkSession.createDataFrame(list(enumerate(p for p, _ in held)), "n bigint, pattern string")
    met = blocks.together(coded, [i for _, i in held])
    one, two = (names.select(F.col("n").alias(c), F.col("pattern").alias(p)) for c, p in (("one", "p1"), ("other", "p2")))
    return met.join(one, "one").join(two, "other").select("p1", "p2")


def apart(pairs: DataFrame, known: DataFrame) -> DataFrame:
    """The pairs whose covers don't overlap.  known is either overlapping()'s table, or lists, as `pattern`, every itemset that some transaction contains: covers
    overlap exactly when the union of the two occurs.  Either way an anti-join replaces the comparison of covers."""
    if "p1" in known.columns:
        return pairs.join(known.select(F.col("p1").alias("pattern1"), F.col("p2").alias("pattern2")), ["pattern1", "pattern2"], "left_anti")
    return pairs.withColumn("pattern", union_text()).join(known.select("pattern"), "pattern", "left_anti").drop("pattern")


def tilings(patterns: DataFrame, known: DataFrame) -> DataFrame:
    """All non-overlapping pairs of the patterns (M33, K11, K12); known as for apart.  Area is the sum of support times length."""
    one, two = sides(patterns)
    return named(apart(one.join(two, (F.col("pattern1") < F.col("pattern2")) & ~F.arrays_overlap("items1", "items2")), known))


def k_tilings(patterns: DataFrame, known: DataFrame, k: int) -> DataFrame:
    """(p1 .. pk, area) of all k-tilings (M32): tilings of one pattern fewer, joined with the pairs that their last pattern forms, and with those of the others."""
    pairs = cut(tilings(patterns, known).select("p1", "p2"))
    area = patterns.select(F.col("pattern"), (F.col("freq") * F.col("size")).alias("a"))
    out = pairs
    for n in range(3, k + 1):
        out = out.join(pairs.select(F.col("p1").alias(f"p{n - 1}"), F.col("p2").alias(f"p{n}")), f"p{n - 1}")
        for j in range(1, n - 1):
            out = out.join(pairs.select(F.col("p1").alias(f"p{j}"), F.col("p2").alias(f"p{n}")), [f"p{j}", f"p{n}"], "left_semi")
    names = [f"p{n}" for n in range(1, k + 1)]
    for n in names:
        out = out.join(area.select(F.col("pattern").alias(n), F.col("a").alias(f"a_{n}")), n)
    return out.select(*names, sum((F.col(f"a_{n}") for n in names), F.lit(0)).cast("bigint").alias("area"))


def named(pairs: DataFrame) -> DataFrame:
    area = F.col("freq1") * F.col("size1") + F.col("freq2") * F.col("size2")
    return pairs.select(F.col("pattern1").alias("p1"), F.col("pattern2").alias("p2"), "freq1", "freq2", area.alias("area"))


def signature(items: str, run: Column, slot: int, seed: int) -> Column:
    """52 parities of an itemset under the coefficients of its slot."""
    return F.aggregate(items, F.lit(0).cast("bigint"), lambda acc, i: acc.bitwiseXOR(draw(F.lit(seed), run, F.lit(slot), i)))


def tiling_cells(patterns: DataFrame, known: DataFrame, runs: DataFrame, m: int, seed: int) -> DataFrame:
    """(run, p1, p2, freq1, freq2, area, depth) of the tilings in each run's cell of m constraints.

    The parity of a pair is the XOR of its constituents' parities under their slots' coefficients, so members of a cell meet by an equi-join on the
    first m parities, with |P|^2 / 2^m candidates instead of |P|^2."""
    low = F.lit((1 << m) - 1).cast("bigint")
    one, two = sides(patterns)
    # one MD5 for each (run, slot, item); patterns only combine them
    items = patterns.select(F.explode("items").alias("item")).distinct()
    coded = runs.crossJoin(F.broadcast(items)).withColumns({f"word{k}": draw(F.lit(seed), F.col("run"), F.lit(k), F.col("item")) for k in (1, 2)})
    by_run = coded.groupBy("run").agg(F.map_from_entries(F.collect_list(F.struct("item", F.struct("word1", "word2")))).alias("codes"))
    sig = lambda k: F.aggregate(f"items{k}", F.lit(0).cast("bigint"), lambda acc, i: acc.bitwiseXOR(F.element_at("codes", i)[f"word{k}"]))
    left = one.crossJoin(by_run).withColumn("sig1", sig(1)).drop("codes")
    right = two.crossJoin(by_run).withColumn("sig2", sig(2).bitwiseXOR(draw(F.lit(seed), F.col("run"), F.lit("parity")))).drop("codes")
    left, right = left.withColumn("cell", F.col("sig1").bitwiseAND(low)), right.withColumn("cell", F.col("sig2").bitwiseAND(low))
    pairs = apart(left.join(right, ["run", "cell"]).where((F.col("pattern1") < F.col("pattern2")) & ~F.arrays_overlap("items1", "items2")), known)
    depth = F.least(trailing_zeros(F.col("sig1").bitwiseXOR(F.col("sig2"))), F.lit(DEEPEST))
    return pairs.select("run", F.col("pattern1").alias("p1"), F.col("pattern2").alias("p2"), "freq1", "freq2", (F.col("freq1") * F.col("size1") + F.col("freq2") * F.col("size2")).alias("area"), depth.alias("depth"))


def first_level(patterns: int) -> int:
    """Constraints with which cells are looked at first: few enough that a cell is hardly ever empty, enough that a run has some thousand candidate pairs."""
    return max(0, math.ceil(math.log2(max(1, patterns * (patterns - 1) // 2))) - 12)


def tiling_estimate(cells: DataFrame, base: int, bound: float, params: EstimateParams = EstimateParams()) -> DataFrame:
    """(run, m, cell_weight, attempt, estimate) from the cells of `base` constraints of params.runs * params.attempts runs: the least m >= base whose cell
    weighs no more than bound; of the attempts of a run the first that has a tiling counts (M13)."""
    return fitting_runs(cells_of(cells.groupBy("run", "depth").agg(F.sum("area").alias("w"), F.count("*").alias("n"))), bound, params, base)


def tiling_sample(patterns: DataFrame, known: DataFrame, total: float, scale: float, n: int, kappa: float, seed: int) -> DataFrame:
    """(sample_id, status, p1, p2, area, n_xor): a tiling drawn by area from one cell in range for each sample (M31); without any tiling (total 0) all fail."""
    from pyspark.sql import Window

    lo, hi = (x * scale for x in cell_range(kappa))
    start = initial_xors(total / scale, kappa)
    runs = runs_table(patterns.sparkSession, n)
    cells = tiling_cells(patterns, known, runs, start, seed)
    key = F.round(F.ln(unit(draw(F.lit(seed), F.lit("pick"), F.col("run"), F.col("p1"), F.col("p2")))) / F.col("area"), 12)
    level = F.least(F.col("depth") - start, F.lit(3)).cast("int")
    each = cells.groupBy("run", level.alias("level")).agg(F.sum("area").alias("w"), F.max(F.struct(key.alias("key"), "p1", "p2", "area")).alias("best"))
    down = Window.partitionBy("run").orderBy(F.desc("level"))
    every = runs.crossJoin(patterns.sparkSession.range(4).select(F.col("id").cast("int").alias("level"))).join(each, ["run", "level"], "left")
    every = every.withColumn("cell_weight", F.coalesce(F.sum("w").over(down), F.lit(0))).withColumn("best", F.max("best").over(down))
    first = every.where(F.col("cell_weight") <= hi).groupBy("run").agg(F.min(F.struct("level", "cell_weight", "best")).alias("c"))
    out = runs.join(first, "run", "left")
    good = (F.col("c.cell_weight") >= lo) | ((F.lit(start) + F.col("c.level")) == 0)
    status = F.when(F.col("c").isNull(), "too_large").when(good & F.col("c.best").isNotNull(), "ok").otherwise("too_small")
    out = out.withColumn("status", status)
    on = F.col("status") == "ok"
    return out.select(F.col("run").alias("sample_id"), "status", *[F.when(on, F.col(f"c.best.{x}")).alias(x) for x in ("p1", "p2", "area")], (F.lit(start) + F.coalesce("c.level", F.lit(3))).cast("int").alias("n_xor"))


class PatternSetSearch:
    """k patterns with their own item variables (M30, M32): depth-first over k slots, XORs over all k * n variables.

    Slot by slot, the generic oracle enumerates a pattern that excludes the items and the covered rows of the slots before; the XOR system carries what they
    have fixed, and the last slot is searched under the rows that are left.  Slots are ordered by their patterns' texts."""

    def __init__(self, oracle: Search, k: int, disjoint_items: bool = True, disjoint_covers: bool = True) -> None:
        self.oracle, self.k, self.items, self.covers = oracle, k, disjoint_items, disjoint_covers

    def solve(self, xors: list[tuple[int, int]], bound: float | None = None) -> tuple[list[tuple[tuple[int, ...], int]], int, bool]:
        """(solutions as (masks, area), weight, overflow)."""
        out, weight = [], 0
        for masks, area in self.slots((), (), xors):
            out.append((masks, area))
            weight += area
            if bound is not None and weight > bound:
                return out, weight, True
        return out, weight, False

    def slots(self, masks: tuple[int, ...], covers: tuple[int, ...], xors: list[tuple[int, int]]) -> Iterator[tuple[tuple[int, ...], int]]:
        data = self.oracle.data
        n = len(data.items)
        slot = len(masks)
        if slot == self.k:
            area = sum(m.bit_count() * data.count(c) for m, c in zip(masks, covers))
            yield masks, area
            return
        # constraints that hold no variable of a later slot bind this slot already
        later = ~((1 << n * (slot + 1)) - 1)
        fixed = sum(m << n * s for s, m in enumerate(masks))
        rows = []
        try:
            system = Gf2System()
            for mask, parity in xors:
                p = parity ^ ((mask & fixed & ((1 << n * slot) - 1)).bit_count() & 1)
                system.add(mask >> n * slot, p)
            rows = [(m, p) for m, p in system.rows if not (m << n * slot) & later]
        except Conflict:
            return
        for mask, freq, _, _ in self.oracle.solve(rows).solutions:
            cover = data.everything
            for j in range(mask.bit_length()):
                if mask >> j & 1:
                    cover &= data.bitmaps[j]
            if self.items and any(mask & m for m in masks) or self.covers and any(cover & c for c in covers):
                continue
            if masks and self.oracle.names(masks[-1]) >= self.oracle.names(mask):
                continue
            yield from self.slots((*masks, mask), (*covers, cover), xors)


def conceptual_clusterings(pairs: DataFrame, transactions: int) -> DataFrame:
    """Tilings whose two covers make up all transactions."""
    return pairs.where(F.col("freq1") + F.col("freq2") == transactions)


def redescriptions(patterns: DataFrame, occurring: DataFrame, left: tuple[str, ...], min_jaccard: float) -> DataFrame:
    """Pairs of patterns over two vocabularies with similar covers (M34): items of the first are of the attributes `left`, those of the second are not."""
    on_left = lambda c: F.forall(c, lambda x: F.substring_index(x, "=", 1).isin(*left))
    off_left = lambda c: F.forall(c, lambda x: ~F.substring_index(x, "=", 1).isin(*left))
    one, two = sides(patterns)
    pairs = one.where(on_left("items1")).join(two.where(off_left("items2"))).withColumn("pattern", union_text())
    both = pairs.join(occurring.select("pattern", F.col("freq").alias("both")), "pattern")
    jaccard = F.col("both") / (F.col("freq1") + F.col("freq2") - F.col("both"))
    return both.where(jaccard >= min_jaccard).select(F.col("pattern1").alias("p1"), F.col("pattern2").alias("p2"), F.round(jaccard, 9).alias("jaccard"))


def association_rules(patterns: DataFrame, min_confidence: float) -> DataFrame:
    """(body, head, freq, confidence) with one item as head (M34): a pattern is joined with the body that it extends."""
    split = F.transform(F.sequence(F.lit(1), F.size("items")), lambda i: F.struct(F.element_at("items", i).alias("head"), F.array_join(F.concat(F.slice("items", F.lit(1), i - 1), F.slice("items", i + 1, F.size("items"))), ",").alias("body")))
    whole = patterns.where("size > 1").select("freq", F.explode(split).alias("s")).select("freq", "s.head", "s.body")
    body = patterns.select(F.col("pattern").alias("body"), F.col("freq").alias("body_freq"))
    return whole.join(body, "body").where(F.col("freq") >= min_confidence * F.col("body_freq")).select("body", "head", "freq", F.round(F.col("freq") / F.col("body_freq"), 9).alias("confidence"))


def two_term_dnf(patterns: DataFrame, occurring: DataFrame) -> DataFrame:
    """(p1, p2, freq, freq_pos, purity) of the unions of two covers (M34); covers may overlap, so what both cover counts once."""
    one = patterns.select(F.col("pattern").alias("pattern1"), F.col("items").alias("items1"), F.col("freq").alias("f1"), F.col("freq_pos").alias("g1"))
    two = patterns.select(F.col("pattern").alias("pattern2"), F.col("items").alias("items2"), F.col("freq").alias("f2"), F.col("freq_pos").alias("g2"))
    pairs = one.join(two, F.col("pattern1") < F.col("pattern2")).withColumn("pattern", union_text())
    both = pairs.join(occurring.select("pattern", F.col("freq").alias("fb"), F.col("freq_pos").alias("gb")), "pattern", "left")
    f, g = F.col("f1") + F.col("f2") - F.coalesce("fb", F.lit(0)), F.col("g1") + F.col("g2") - F.coalesce("gb", F.lit(0))
    return both.select(F.col("pattern1").alias("p1"), F.col("pattern2").alias("p2"), f.alias("freq"), g.alias("freq_pos"), F.round(F.greatest(g, f - g) / f, 9).alias("purity"))
