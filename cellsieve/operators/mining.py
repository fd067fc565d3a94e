"""Enumeration of itemsets with DataFrame operators (O9-O17, B9, B10): dictionary, condensing, frequent, closed, maximal, labelled.

A pattern table has pattern (items joined by commas), items, size, freq, freq_pos.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..spec import QUALITIES, Constraints, Quality
from . import blocks

PATTERN = ("pattern", "items", "size", "freq", "freq_pos")


def condense(tx: DataFrame) -> DataFrame:
    """(items, mult, pos): equal transactions become one with a multiplicity."""
    return tx.groupBy("items").agg(F.count("*").alias("mult"), F.coalesce(F.sum(F.coalesce(F.col("label"), F.lit(False)).cast("bigint")), F.lit(0)).alias("pos"))


def item_dictionary(tx: DataFrame) -> DataFrame:
    """(item, freq, rank): ranks by rising support, then name (O9).  Only the dictionary, not the data, passes one window."""
    freq = tx.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("freq"))
    return freq.withColumn("rank", F.row_number().over(Window.orderBy("freq", "item")))


def dataset_stats(tx: DataFrame) -> DataFrame:
    """One row: transactions, distinct transactions, ones, items, density."""
    rows = condense(tx).agg(F.sum("mult").alias("transactions"), F.count("*").alias("distinct_transactions"), F.sum(F.size("items") * F.col("mult")).alias("ones"))
    n = tx.select(F.explode("items").alias("item")).agg(F.countDistinct("item").alias("n_items"))
    return rows.crossJoin(n).withColumn("density", F.round(F.col("ones") / (F.col("transactions") * F.col("n_items")), 6))


def without_infrequent(tx: DataFrame, minsup: int) -> DataFrame:
    """Transactions cut down to frequent items; those that become empty stay, since they count as transactions."""
    frequent = tx.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("n")).where(F.col("n") >= minsup).agg(F.collect_set("item").alias("frequent"))
    return tx.crossJoin(frequent).withColumn("items", F.array_sort(F.array_intersect("items", "frequent"))).drop("frequent")


def finished(patterns: DataFrame) -> DataFrame:
    return patterns.select(F.array_join("items", ",").alias("pattern"), "items", F.size("items").alias("size"), "freq", "freq_pos")


def frequent_cube(rows: DataFrame, attributes: Sequence[str], minsup: int, label: str = "label") -> DataFrame:
    """Frequent itemsets of attribute-value data: each cell of the cube is one itemset.

    Rows are condensed before they are expanded into cells, so the expansion works on distinct combinations."""
    condensed = rows.groupBy(*attributes).agg(F.count("*").alias("mult"), F.sum(F.col(label).cast("bigint")).alias("pos"))
    # a row becomes 2 ** attributes of them: few, short rows must not end up in one partition
    condensed = condensed.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), rows.sparkSession.sparkContext.defaultParallelism))
    cells = condensed.cube(*attributes).agg(F.sum("mult").alias("freq"), F.sum("pos").alias("freq_pos"), *[F.grouping(a).alias(f"out_{a}") for a in attributes]).where(F.col("freq") >= minsup)
    # a null that stands in the data is no item: its cell would repeat the one in which the attribute is left out
    for a in attributes:
        cells = cells.where((F.col(f"out_{a}") == 1) | F.col(a).isNotNull())
    items = F.array_sort(F.filter(F.array(*attributes), lambda x: x.isNotNull()))
    return finished(cells.select(items.alias("items"), "freq", "freq_pos").where(F.size("items") > 0))


#: Frequent items beyond which the pairs of items are too many to be counted in every block.
DENSE_ITEMS = 2_000


def frequent_levelwise(tx: DataFrame, minsup: int, max_len: int) -> DataFrame:
    """Frequent itemsets of baskets up to max_len, level by level."""
    return frequent_in(blocks.coded(tx), minsup, max_len)


def frequent_in(coded: DataFrame, minsup: int, max_len: int) -> DataFrame:
    """The same from blocks.coded: a level's candidates are counted over bitmaps, block by block, and only their counts leave the worker."""
    known = blocks.item_counts(coded).where(F.col("freq") >= max(1, minsup))
    if known.count() > DENSE_ITEMS:
        return frequent_by_joins(blocks.decoded(coded), minsup, max_len)
    return finished(blocks.frequent(coded, sorted((r["item"], r["freq"], r["freq_pos"]) for r in known.collect()), max(1, minsup), max_len))


def frequent_by_joins(tx: DataFrame, minsup: int, max_len: int) -> DataFrame:
    """frequent_levelwise for many frequent items of which a row holds few: the work and the shuffle grow with the itemsets of a row, not with the pairs of items.

    Equal transactions are condensed and numbered first.  A level's occurrences are (row, itemset) pairs; joining them with the row's frequent items that come later
    gives the next level's, and a semi-join with the frequent itemsets drops the rest before the next level."""
    rows = cut(condense(tx.select(F.array_sort(F.array_distinct("items")).alias("items"), "label")).withColumn("row", F.monotonically_increasing_id()))
    each = rows.select("row", "mult", "pos", F.explode("items").alias("item"))
    known = each.groupBy("item").agg(F.sum("mult").alias("n")).where(F.col("n") >= minsup).select("item")
    single = cut(each.join(known, "item", "left_semi"))
    # a level is read twice, by its count and by the next level, so each is kept in the shared folder
    occurrences = single.select("row", "mult", "pos", F.array("item").alias("items"), F.col("item").alias("last"))
    out = None
    for size in range(1, max_len + 1):
        level = occurrences.groupBy("items").agg(F.sum("mult").alias("freq"), F.sum("pos").alias("freq_pos")).where(F.col("freq") >= minsup)
        out = level if out is None else out.union(level)
        if size < max_len:
            kept = occurrences.join(level.select("items"), "items", "left_semi")
            occurrences = cut(kept.join(single.select("row", "item"), "row").where("item > last").select("row", "mult", "pos", F.concat("items", F.array("item")).alias("items"), F.col("item").alias("last")))
            if occurrences.isEmpty():
                break
    return finished(out)


def frequent_fpgrowth(tx: DataFrame, minsup: int, transactions: int) -> DataFrame:
    """(pattern, size, freq) by Spark's own miner, as an independent count."""
    from pyspark.ml.fpm import FPGrowth

    model = FPGrowth(itemsCol="items", minSupport=(minsup - 0.5) / transactions).fit(tx.select("items"))
    items = F.array_sort("items")
    return model.freqItemsets.select(F.array_join(items, ",").alias("pattern"), F.size(items).alias("size"), "freq").where(F.col("freq") >= minsup)


def one_smaller(patterns: DataFrame) -> DataFrame:
    """(sub, freq) of all itemsets that lack one item of a pattern."""
    dropped = F.transform(F.sequence(F.lit(1), F.size("items")), lambda i: F.concat(F.slice("items", F.lit(1), i - 1), F.slice("items", i + 1, F.size("items"))))
    return patterns.where("size > 1").select(F.explode(dropped).alias("sub"), "freq").select(F.array_join("sub", ",").alias("pattern"), "freq")


def closed_itemsets(patterns: DataFrame) -> DataFrame:
    """Patterns without a superset of equal support (O17).  A superset of equal support is frequent too, so one item more and frequent itemsets
    are enough: an equi-join on (pattern, freq)."""
    return patterns.join(one_smaller(patterns).distinct(), ["pattern", "freq"], "left_anti").select(*PATTERN)


def maximal_itemsets(patterns: DataFrame) -> DataFrame:
    return patterns.join(one_smaller(patterns).select("pattern").distinct(), "pattern", "left_anti").select(*PATTERN)


def free_generators(patterns: DataFrame, transactions: int) -> DataFrame:
    """Patterns none of whose one-smaller subsets has equal support (K8)."""
    dropped = F.transform(F.sequence(F.lit(1), F.size("items")), lambda i: F.concat(F.slice("items", F.lit(1), i - 1), F.slice("items", i + 1, F.size("items"))))
    subs = patterns.where("size > 1").select(F.col("pattern").alias("whole"), "freq", F.explode(dropped).alias("sub")).select("whole", "freq", F.array_join("sub", ",").alias("pattern"))
    not_free = subs.join(patterns.select("pattern", "freq"), ["pattern", "freq"], "left_semi").select(F.col("whole").alias("pattern")).distinct()
    return patterns.join(not_free, "pattern", "left_anti").where((F.col("size") > 1) | (F.col("freq") < transactions)).select(*PATTERN)


def constrained(patterns: DataFrame, c: Constraints) -> DataFrame:
    """The patterns that meet the constraints; patterns must hold all frequent itemsets if c asks for closed ones."""
    out = patterns.where(F.col("freq") >= c.minsup) if c.minsup else patterns
    if c.closed:
        out = closed_itemsets(out)
    out = out.where(F.col("size") >= c.min_len)
    if c.max_len is not None:
        out = out.where(F.col("size") <= c.max_len)
    if c.max_sup is not None:
        out = out.where(F.col("freq") <= c.max_sup)
    if c.min_pos:
        out = out.where(F.col("freq_pos") >= c.min_pos)
    for i in c.must:
        out = out.where(F.array_contains("items", i))
    for i in c.must_not:
        out = out.where(~F.array_contains("items", i))
    for a, b in c.implies:
        out = out.where(~F.array_contains("items", a) | F.array_contains("items", b))
    if c.one_per_attribute:
        names = F.transform("items", lambda x: F.substring_index(x, "=", 1))
        out = out.where(F.size(F.array_distinct(names)) == F.size("items"))
    return out


def quality_between(patterns: DataFrame, quality: Quality | str, least: float, most: float) -> DataFrame:
    """The patterns whose quality's integer weight lies between two bounds (K9), for slices of high tilt and for the right tail."""
    q = QUALITIES[quality] if isinstance(quality, str) else quality
    return patterns.where(F.expr(q.spark).between(least, most))


def support(patterns: DataFrame, tx: DataFrame) -> DataFrame:
    """(pattern, support) of given itemsets in any transactions (O13): equal transactions are joined once, by item, and complete ones kept."""
    rows = tx.groupBy("items").agg(F.count("*").alias("mult")).select(F.unhex(F.md5(F.array_join("items", "\x1f"))).alias("row"), "mult", F.explode("items").alias("item"))
    wanted = patterns.select("pattern", "size", F.explode("items").alias("item"))
    full = rows.join(wanted, "item").groupBy("row", "mult", "pattern", "size").agg(F.count("*").alias("n")).where("n = size")
    return patterns.select("pattern").join(full.groupBy("pattern").agg(F.sum("mult").alias("support")), "pattern", "left").select("pattern", F.coalesce("support", F.lit(0)).alias("support"))


def tidsets(tx: DataFrame) -> DataFrame:
    """(item, block, bits): vertical bitmaps in blocks of 32768 numbered transactions."""
    t = F.col("tid").cast("bigint")
    rows = tx.select(F.explode("items").alias("item"), F.bitmap_bucket_number(t).alias("block"), F.bitmap_bit_position(t).alias("bit"))
    return rows.groupBy("item", "block").agg(F.bitmap_construct_agg("bit").alias("bits"))


def top_k(patterns: DataFrame, k: int, by: str) -> DataFrame:
    """The k patterns of the largest value of the expression `by`; ties by text."""
    return patterns.withColumn("quality", F.expr(by).cast("bigint")).orderBy(F.desc("quality"), "pattern").limit(k)
