"""Near-duplicate embeddings by cross-polytope hashing.

A vector is scaled to length 1, padded to a power of two, and turned by three rounds of random signs and a fast Hadamard transform.  The
coordinate of the largest magnitude, with its sign, is one hash; HASHES of them make a bucket of one of TABLES tables.  Multiprobe: a vector also stands
in the PROBES next likely buckets, those in which one hash is replaced by its runner-up, nearest runner-up first.  Vectors that share a bucket
are candidates; each distinct candidate pair is verified by its exact cosine.

near_pairs lists the pairs, whose number grows with the square of a group of near copies.  near_classes gives a row for each id, with its class and the
number of its links, and lists no pairs: equal vectors are one node, a bucket passes on only which of its members hang together, and all pairs
of a class are then compared, so within a class no link is lost, not even those that share no bucket.  A class of m vectors costs m * m comparisons.

Definitions for odd input.  Null, empty and all-zero vectors, vectors with a null, infinite or missing number, and rows with a null id have no partners.
Vectors of different lengths are never partners.  Rows of one id: an id is never its own partner; a pair is listed once, with its largest cosine.
Of classes: an id without partners is alone in its class; all vectors of an id are in its class; null ids have no row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix64, times, written
from .graph import components

TABLES = 10
HASHES = 3
PROBES = 3
THRESHOLD = 0.9
SEED = 5
#: Members of a group that one task compares with so many others.
BLOCK = 2_000


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of the rows, unscaled."""
    n, h = x.shape[1], 1
    while h < n:
        y = x.reshape(len(x), n // (2 * h), 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(len(x), n)
        h *= 2
    return x


def signs(seed: int, n: int) -> np.ndarray:
    bits = mix64(np.arange(1, n + 1, dtype=np.uint64) * times(1) ^ times(seed))
    return np.where(bits & np.uint64(1), 1.0, -1.0).astype(np.float32)


def buckets(x: np.ndarray, tables: int = TABLES, hashes: int = HASHES, probes: int = PROBES, seed: int = SEED) -> np.ndarray:
    """uint64 bucket names, rows x (tables * (1 + probes)), of unit vectors."""
    d = 1 << max(1, (x.shape[1] - 1).bit_length())
    x = np.pad(x.astype(np.float32), ((0, 0), (0, d - x.shape[1])))
    rows = np.arange(len(x))
    out = []
    for t in range(tables):
        first, second, gap = [], [], []
        for k in range(hashes):
            y = x
            for r in range(3):
                y = hadamard(y * signs(((seed * 101 + t) * 101 + k) * 101 + r, d))
            size = np.abs(y)
            top = size.argmax(1)
            best = size[rows, top]
            first.append(2 * top + (y[rows, top] < 0))
            size[rows, top] = -1
            nxt = size.argmax(1)
            second.append(2 * nxt + (y[rows, nxt] < 0))
            gap.append((best - size[rows, nxt]) / np.maximum(best, 1e-30))
        first, second, gap = np.array(first), np.array(second), np.array(gap)
        # replaced sets of hashes, by the sum of gaps; the empty set is the bucket itself
        sets = np.array([[m >> k & 1 for k in range(hashes)] for m in range(1 << hashes)])
        order = np.argsort(sets @ gap, axis=0, kind="stable")[: 1 + probes]
        for o in order:
            code = np.full(len(x), t + 1, np.uint64)
            for k in range(hashes):
                code = code * np.uint64(1_000_003) + np.where(sets[o, k], second[k], first[k]).astype(np.uint64)
            out.append(mix64(code))
    return np.stack(out, axis=1)


def clean(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    v = F.col(vec_col).cast("array<double>")
    good = F.col(id_col).isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    return df.where(F.coalesce(good, F.lit(False))).select(F.col(id_col).cast("bigint").alias("id"), F.col(vec_col).cast("array<float>").alias("v"))


@F.pandas_udf(T.DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    if not len(a):
        return pd.Series([], dtype="float64")
    size, out = a.map(len).to_numpy(), np.empty(len(a))
    for n in np.unique(size):
        x, y = np.stack(a[size == n]).astype(np.float64), np.stack(b[size == n]).astype(np.float64)
        out[size == n] = (x * y).sum(1) / np.sqrt((x * x).sum(1) * (y * y).sum(1))
    return pd.Series(out)


def in_buckets(vectors: DataFrame, tables: int, hashes: int, probes: int) -> DataFrame:
    """(bucket, rid) of vectors (rid, v)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 4096):
                b = whole.slice(at, 4096)
                sizes = b.column("v").value_lengths().to_numpy(zero_copy_only=False)
                for n in np.unique(sizes):
                    part = b.filter(pa.array(sizes == n))
                    x = part.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, n).astype(np.float64)
                    x /= np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-300)
                    code = mix64(buckets(x, tables, hashes, probes) ^ times(int(n)))
                    width = code.shape[1]
                    yield pa.RecordBatch.from_arrays([pa.array(code.ravel().view(np.int64)), pa.array(np.repeat(part.column("rid").to_numpy(), width))], ["bucket", "rid"])

    return vectors.select("rid", "v").mapInArrow(run, "bucket bigint, rid bigint")


def near_pairs(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", *, threshold: float = THRESHOLD, tables: int = TABLES, hashes: int = HASHES, probes: int = PROBES) -> DataFrame:
    """(id_a, id_b, cosine) of pairs id_a < id_b whose cosine is at least the threshold, rounded to six places."""

    rows = written(clean(df, id_col, vec_col).groupBy("id", "v").count().select(F.monotonically_increasing_id().alias("rid"), "id", "v"), "vectors")
    members = written(in_buckets(rows, tables, hashes, probes), "buckets")
    crowd = members.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1").select("bucket")
    members = members.join(crowd, "bucket")
    pairs = members.select("bucket", F.col("rid").alias("a")).join(members.select("bucket", F.col("rid").alias("b")), "bucket").where("a < b").select("a", "b").distinct()
    left = rows.select(F.col("rid").alias("a"), F.col("id").alias("ia"), F.col("v").alias("va"))
    right = rows.select(F.col("rid").alias("b"), F.col("id").alias("ib"), F.col("v").alias("vb"))
    scored = pairs.join(left, "a").join(right, "b").where("ia != ib and size(va) = size(vb)").select(F.least("ia", "ib").alias("id_a"), F.greatest("ia", "ib").alias("id_b"), cosine("va", "vb").alias("cosine"))
    return scored.where(F.col("cosine") >= threshold).groupBy("id_a", "id_b").agg(F.round(F.max("cosine"), 6).alias("cosine"))


def sections(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
    """Sorted rows as batches of whole groups (key, i, j, size), with the bounds of the groups."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        b = pa.concat_batches([*held, b])
        key = np.stack([b.column(c).to_numpy() for c in ("key", "i", "j", "size")])
        at = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(0)) + 1
        if len(at):
            yield b.slice(0, at[-1]), np.concatenate([[0], at])
            b = b.slice(at[-1])
        held = [b] if b.num_rows else []
    for b in held:
        yield b, np.array([0, b.num_rows])


def above(x: np.ndarray, y: np.ndarray, threshold: float) -> np.ndarray:
    """Whether the cosines of the rows of x and y reach the threshold, for each of a stack of groups."""
    with np.errstate(invalid="ignore", divide="ignore"):
        return (x @ y.swapaxes(1, 2)) / np.sqrt((x * x).sum(2)[:, :, None] * (y * y).sum(2)[:, None, :]) >= threshold


def compared(batches: Iterator[pa.RecordBatch], threshold: float, cells: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray, pa.RecordBatch]]:
    """(at, near, batch): stacks of groups of one size, their rows in the batch and which of them are linked.  Of two blocks only the pairs across are compared."""
    for b, bounds in sections(batches):
        lists, block, size = b.column("v"), b.column("block").to_numpy(), b.column("size").to_numpy()
        flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        start = np.cumsum(size) - size
        first, n = bounds[:-1], np.diff(bounds)
        two = b.column("i").to_numpy()[first] != b.column("j").to_numpy()[first]
        some = (n > 1) & (~two | (block[first] != block[bounds[1:] - 1]))
        first, n, two = first[some], n[some], two[some]
        for s, d, t in np.unique(np.stack([n, size[first], two], axis=1), axis=0):
            same = first[(n == s) & (size[first] == d) & (two == t)]
            step = max(1, int(cells // (s * max(s, d))))
            for k in range(0, len(same), step):
                at = same[k : k + step, None] + np.arange(s)
                x = flat[start[at][:, :, None] + np.arange(d)]
                near = np.zeros((len(at), s, s), bool)
                # with two blocks one group a step, so that it can be split; large groups by stretches of rows
                for g in range(len(at)) if t else [slice(None)]:
                    own = slice(g, g + 1) if t else g
                    p = int((block[at[own]] == block[at[own]][:, :1]).sum()) if t else s
                    for lo in range(0, p, 256):
                        hi = min(lo + 256, p)
                        near[own, lo:hi, p % s :] = above(x[own, lo:hi], x[own, p % s :], threshold)
                    if t:
                        near[own, p:, :p] = near[own, :p, p:].swapaxes(1, 2)
                near[:, np.arange(s), np.arange(s)] = False
                yield at, near, b


def hung(near: np.ndarray) -> np.ndarray:
    """For each member of each group the smallest member that hangs together with it by links."""
    part = np.broadcast_to(np.arange(near.shape[1], dtype=np.int32), near.shape[:2])
    while True:
        low = np.minimum(part, np.where(near, part[:, None, :], np.int32(near.shape[1])).min(2))
        low = np.take_along_axis(low, low, 1)
        if (low == part).all():
            return part
        part = low


def side_by_side(groups: DataFrame, vectors: DataFrame, block: int) -> DataFrame:
    """Groups (key, rid, n) with their vectors, sorted by group; one of more than block members is cut into blocks, and each pair of blocks is a group of its own."""
    blocks = F.ceil(F.col("n") / block).cast("bigint")
    cut = groups.withColumn("block", F.pmod(F.xxhash64("rid"), blocks)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), blocks - 1)))
    cut = cut.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rid")
    return cut.join(vectors.withColumn("size", F.size("v").cast("bigint")), "rid").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "size", "block")


def near_classes(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", *, threshold: float = THRESHOLD, tables: int = TABLES, hashes: int = HASHES, probes: int = PROBES, block: int = BLOCK) -> DataFrame:
    """(id, class, links) for every id: class is the smallest id that links lead to, links the number of other ids whose cosine is at least the threshold.

    1. Equal vectors become one node, however many ids have them.
    2. In each bucket all members are compared, and each is tied to the smallest one that hangs together with it; components of the ties are the classes.
    3. In each class all members are compared, and each gets the number of ids that have its partners.  Ids of several vectors may meet a partner
       twice, so only the pairs of their vectors are listed, and their partners counted without repeats.
    """

    def ties(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, near, b in compared(batches, threshold):
            rid, low = b.column("rid").to_numpy()[at], hung(near)
            on = low != np.arange(at.shape[1])
            if on.any():
                yield pa.RecordBatch.from_arrays([pa.array(np.take_along_axis(rid, low, 1)[on]), pa.array(rid[on])], ["a", "b"])

    def degrees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, near, b in compared(batches, threshold):
            rid, ids, several = (b.column(c).to_numpy(zero_copy_only=False)[at] for c in ("rid", "single", "several"))
            n = (near.astype(np.float64) @ ids[:, :, None].astype(np.float64))[:, :, 0].astype(np.int64)
            on = n > 0
            yield pa.RecordBatch.from_arrays([pa.array(rid[on]), pa.nulls(int(on.sum()), pa.int64()), pa.array(n[on])], ["rid", "other", "n"])
            if several.any():
                g, x, y = np.nonzero(near & (several[:, :, None] | several[:, None, :]))
                yield pa.RecordBatch.from_arrays([pa.array(rid[g, x]), pa.array(rid[g, y]), pa.array(np.zeros(len(g), np.int64))], ["rid", "other", "n"])

    held = written(clean(df, id_col, vec_col).withColumn("mark", F.unhex(F.md5(F.col("v").cast("string")))), "vectors")
    nodes = written(held.groupBy("mark").agg(F.first("v").alias("v")).withColumn("rid", F.monotonically_increasing_id()), "nodes")
    owners = held.select("id", "mark").distinct().join(nodes.select("mark", "rid"), "mark")
    owners = written(owners.select("id", "rid", (F.count("*").over(Window.partitionBy("id")) > 1).alias("several")), "owners")
    odd = owners.where("several").select("id", "rid")
    vectors = nodes.select("rid", "v").join(owners.groupBy("rid").agg(F.count_if(~F.col("several")).alias("single"), F.max("several").alias("several")), "rid")

    members = written(in_buckets(nodes, tables, hashes, probes), "buckets").withColumnRenamed("bucket", "key")
    crowd = members.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    found = side_by_side(members.join(crowd, "key"), nodes.select("rid", "v"), block).mapInArrow(ties, "a bigint, b bigint")
    # the vectors of one id are in one class
    own = odd.withColumn("a", F.min("rid").over(Window.partitionBy("id"))).select("a", F.col("rid").alias("b"))
    roots = written(components(found.union(own).distinct()).select(F.col("root").alias("key"), F.col("node").alias("rid")), "roots")

    sizes = roots.groupBy("key").agg(F.count("*").alias("n"))
    met = written(side_by_side(roots.join(sizes, "key"), vectors, block).mapInArrow(degrees, "rid bigint, other bigint, n bigint"), "links")
    pairs = met.where("other is not null").select("rid", "other").union(odd.select("rid", F.col("rid").alias("other")).distinct())
    seen = pairs.join(odd.select(F.col("id").alias("met"), F.col("rid").alias("other")), "other")
    per_node = met.groupBy("rid").agg(F.sum("n").alias("n")).join(seen.groupBy("rid").agg(F.count_distinct("met").alias("m")), "rid", "full")
    links = F.col("single") - 1 + F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))
    one = owners.where("not several").select("id", "rid").join(vectors.select("rid", "single"), "rid").join(per_node, "rid", "left").select("id", "rid", links.alias("links"))
    reach = odd.join(pairs, "rid").select("id", "other").distinct().join(vectors.select(F.col("rid").alias("other"), "single"), "other").groupBy("id").agg(F.sum("single").alias("s"))
    more = odd.join(seen, "rid").groupBy("id").agg(F.count_distinct("met").alias("m")).join(reach, "id").select("id", (F.col("s") + F.col("m") - 1).alias("links"))
    more = odd.groupBy("id").agg(F.min("rid").alias("rid")).join(more, "id").select("id", "rid", "links")

    placed = one.union(more).join(roots, "rid", "left").withColumn("key", F.coalesce("key", "rid"))
    placed = placed.join(placed.groupBy("key").agg(F.min("id").alias("class")), "key").select("id", "class", "links")
    ids = df.select(F.col(id_col).cast("bigint").alias("id")).where("id is not null").distinct()
    return ids.join(placed, "id", "left").select("id", F.coalesce("class", "id").alias("class"), F.coalesce("links", F.lit(0).cast("bigint")).alias("links"))


def near_pairs_sql(threshold: float = THRESHOLD, table: str = "embeddings") -> str:
    return f"""
WITH v AS (SELECT DISTINCT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM {table} WHERE vec_id IS NOT NULL AND len(embedding) > 0)
SELECT a.vec_id AS id_a, b.vec_id AS id_b, round(max(list_cosine_similarity(a.e, b.e)), 6) AS cosine FROM v a JOIN v b ON a.vec_id < b.vec_id AND len(a.e) = len(b.e)
WHERE list_cosine_similarity(a.e, b.e) >= {threshold} GROUP BY 1, 2"""


def near_classes_sql(threshold: float = THRESHOLD, table: str = "embeddings") -> str:
    return f"""
WITH RECURSIVE ids AS (SELECT DISTINCT vec_id FROM {table} WHERE vec_id IS NOT NULL),
p AS ({near_pairs_sql(threshold, table)}),
l AS (SELECT id_a AS a, id_b AS b FROM p UNION ALL SELECT id_b, id_a FROM p),
reach AS (SELECT vec_id AS a, vec_id AS b FROM ids UNION SELECT r.a, l.b FROM reach r JOIN l ON r.b = l.a),
c AS (SELECT a, min(b) AS class_id FROM reach GROUP BY a)
SELECT vec_id, class_id, (SELECT count(*) FROM l WHERE l.a = vec_id) AS links FROM ids JOIN c ON a = vec_id"""
