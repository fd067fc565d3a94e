"""Near-duplicate documents by dart MinHash: weighted signatures, banded joining, verified links, components.

A document is a bag of word shingles, a shingle's weight is its count.  Every shingle owns the quarter plane
(weight, rank), cut into dyadic blocks; each block receives a Poisson number of darts that depends on the shingle
and the block alone.  A document holds a dart when the dart's weight is below the shingle's weight in it.  Each dart
has a coordinate; the signature keeps for each coordinate the dart of smallest rank, so two documents agree in a coordinate with
probability equal to their weighted Jaccard similarity.  Work per document grows with shingles + k log k, not shingles * k.

Definitions for odd input.  Words are maximal runs of letters, digits and underscores, lower-cased; a text shorter than a
shingle is one shingle; a text with no word counts as one shingle made of the text without outer white space.  A null, empty
or blank text has no signature: it is alone in its group and stays.  Repeated rows are copies of each other.  Of a group the
row with the smallest (doc_id, row hash) stays, null doc_id last.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import GOLDEN, U64, chunks, mix64, times, unit, written
from .graph import components

WORD = re.compile(r"\w+")
K = 192
ROWS = 4
SHINGLE = 3
THRESHOLD = 0.45
CACHE = 400_000
#: Members of a bucket that one task compares with so many others.
BLOCK = 2_000
#: Rows (1,024 at most) and bytes of texts signed at a time; the darts thrown for them take some 100 times the bytes.
SLICE_ROWS = 250
SLICE_BYTES = 1_000_000


@lru_cache(None)
def poisson_cdf(mean: float) -> np.ndarray:
    """Cumulative Poisson probabilities up to where doubles end."""
    n = np.arange(int(mean + 12 * mean**0.5 + 40))
    log = n * np.log(mean) - mean - np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, len(n))))])
    return np.minimum(np.cumsum(np.exp(log)), 1.0)


class Shingler:
    """Texts to (row, shingle hash, count).  Keeps hashes of words seen, and forgets them all at CACHE words."""

    def __init__(self, n: int = SHINGLE) -> None:
        self.n, self.seen = n, {}

    def hashes(self, words: list[str]) -> list[int]:
        seen = self.seen
        try:
            return [seen[w] for w in words]
        except KeyError:
            if len(seen) > CACHE:
                seen.clear()
            for w in words:
                if w not in seen:
                    seen[w] = xxhash.xxh3_64_intdigest(w)
            return [seen[w] for w in words]

    def bags(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        flat, lengths = [], np.zeros(len(texts), np.int64)
        for i, t in enumerate(texts):
            if not t:
                continue
            words = WORD.findall(t.lower())
            if not words:
                t = t.strip()
                words = [t] if t else []
            flat += self.hashes(words)
            lengths[i] = len(words)
        h = np.array(flat, U64)
        if not len(h):
            return np.zeros(0, np.int64), np.zeros(0, U64), np.zeros(0, np.int64)
        ends = np.cumsum(lengths)
        # a text of fewer words than a shingle gives one shingle of all its words
        left = np.repeat(ends, lengths) - np.arange(len(h))
        starts = left >= np.minimum(self.n, np.repeat(lengths, lengths))
        at = np.flatnonzero(starts)
        room = left[at]
        out = np.zeros(len(at), U64)
        for j in range(self.n):
            inside = room > j
            term = np.where(inside, h[np.minimum(at + j, len(h) - 1)], U64(0))
            out = mix64(out * U64(0x100000001B3) + term + times(j + 1))
        row = np.repeat(np.arange(len(texts)), lengths)[at]
        key = (out >> U64(10)) | (row.astype(U64) << U64(54))  # at most 1024 rows
        key.sort()
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        count = np.diff(np.append(first, len(key)))
        key = key[first]
        return (key >> U64(54)).astype(np.int64), key << U64(10), count


def darts(row: np.ndarray, h: np.ndarray, weight: np.ndarray, limit: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row * k + coordinate, rank, dart) of all darts that the rows hold with a rank below limit[row]."""
    slots, ranks, names = [], [], []
    nu = 0
    while len(row):
        low_w, high_w = 2.0**nu - 1, 2.0 ** (nu + 1) - 1
        on = weight > low_w
        row, h, weight = row[on], h[on], weight[on]
        if not len(row):
            break
        r_row, r_h, r_w, rho = row, h, weight, 0
        while True:
            low_r, high_r = (0.0, 1.0) if rho == 0 else (2.0 ** (rho - 1), 2.0**rho)
            on = limit[r_row] > low_r
            r_row, r_h, r_w = r_row[on], r_h[on], r_w[on]
            if not len(r_row):
                break
            seed = mix64(r_h + times(nu * 64 + rho + 1))
            count = np.searchsorted(poisson_cdf((high_w - low_w) * (high_r - low_r)), unit(seed), side="right")
            at = np.repeat(np.arange(len(seed)), count)
            nth = np.arange(len(at)) - np.repeat(np.cumsum(count) - count, count)
            one = mix64(seed[at] + (nth.astype(U64) + U64(1)) * U64(0xD1B54A32D192ED03))
            two = mix64(one + GOLDEN)
            rank = low_r + (high_r - low_r) * unit(two)
            held = (rank < limit[r_row[at]]) & (low_w + (high_w - low_w) * unit(one) < r_w[at])
            at, one, two = at[held], one[held], two[held]
            slots.append(r_row[at] * k + ((one & U64(0x7FF)) % U64(k)).astype(np.int64))
            ranks.append(rank[held])
            names.append(((two * U64(0xFF51AFD7ED558CCD)) >> U64(32)).astype(np.uint32))
            rho += 1
        nu += 1
    if not slots:
        return np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.uint32)
    return np.concatenate(slots), np.concatenate(ranks), np.concatenate(names)


def signatures(row: np.ndarray, h: np.ndarray, weight: np.ndarray, n_rows: int, k: int = K) -> np.ndarray:
    """n_rows x k uint32; rows without elements are all zero.  Where a coordinate got no dart the row is thrown again with twice the ranks."""
    out = np.zeros((n_rows, k), np.uint32)
    total = np.bincount(row, weight, n_rows)
    throws = k * np.log(k) + 2.0 * k
    todo = total > 0
    while todo.any():
        on = todo[row]
        limit = np.where(todo, throws / np.maximum(total, 1e-300), 0.0)
        slot, rank, name = darts(row[on], h[on], weight[on].astype(np.float64), limit, k)
        best = np.full(n_rows * k, np.inf)
        np.minimum.at(best, slot, rank)
        won = rank == best[slot]
        sig = np.zeros(n_rows * k, np.uint32)
        sig[slot[won]] = name[won]
        done = todo & np.isfinite(best).reshape(n_rows, k).all(1)
        out[done] = sig.reshape(n_rows, k)[done]
        todo &= ~done
        throws *= 2
    return out


def row_key(id_col: str, text_col: str) -> Column:
    """128 bits of the row, so that no two rows of any table share them by chance."""
    return F.unhex(F.md5(F.concat(F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.lit(":"), F.coalesce(F.concat(F.lit("="), F.col(text_col).cast("string")), F.lit("null")))))


def signing(shingler: Shingler, k: int, batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What sign() gives, for batches of rid, id and text, a slice at a time."""
    for whole in batches:
        for b in chunks(whole, "text", SLICE_ROWS, SLICE_BYTES):
            row, h, w = shingler.bags(b.column("text").to_pylist())
            sig = signatures(row, h, w, b.num_rows, k)
            has = np.bincount(row, minlength=b.num_rows) > 0
            yield pa.RecordBatch.from_arrays([b.column("rid"), b.column("id"), pa.array([s.tobytes() if x else None for s, x in zip(sig, has)], pa.binary())], ["rid", "id", "sig"])


def sign(docs: DataFrame, id_col: str, text_col: str, shingle: int, k: int) -> DataFrame:
    """(rid, id, sig): sig is null for texts without any shingle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return signing(Shingler(shingle), k, batches)

    src = docs.select(row_key(id_col, text_col).alias("rid"), F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "rid binary, id bigint, sig binary")


@F.pandas_udf(T.FloatType())
def agreement(a: pd.Series, b: pd.Series) -> pd.Series:
    """Share of equal coordinates, which estimates the weighted Jaccard similarity."""
    if not len(a):
        return pd.Series([], dtype="float32")
    x = np.frombuffer(b"".join(a), np.uint32).reshape(len(a), -1)
    y = np.frombuffer(b"".join(b), np.uint32).reshape(len(b), -1)
    return pd.Series((x == y).mean(1).astype(np.float32))


def linked(group: pd.DataFrame, threshold: float) -> pd.DataFrame:
    """Links (a, b) of one block, or pair of blocks, of a bucket, enough to connect all members that agree, but for pairs whose members both match the
    bucket's hub.  Members have node, sig, free (doesn't match the hub) and block."""
    group = group.sort_values("node")
    node, free, block = group["node"].to_numpy(), group["free"].to_numpy(), group["block"].to_numpy()
    sig = np.frombuffer(b"".join(group["sig"]), np.uint32).reshape(len(node), -1)
    part, two = np.arange(len(node)), block.min() != block.max()
    a, b = [], []
    for x in np.flatnonzero(free):
        # each pair once; those that are connected already need no look
        other = (part != part[x]) & (~free | (np.arange(len(node)) > x))
        if two:
            other &= block != block[x]
        at = np.flatnonzero(other)
        at = at[(sig[at] == sig[x]).mean(1) >= threshold]
        if len(at):
            a.append(np.full(len(at), node[x]))
            b.append(node[at])
            part[np.isin(part, part[at])] = part[x]
    return pd.DataFrame({"a": np.concatenate([*a, np.zeros(0, np.int64)]), "b": np.concatenate([*b, np.zeros(0, np.int64)])})


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, shingle: int = SHINGLE, k: int = K, rows: int = ROWS, threshold: float = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """(rid, id, copies, group, keep) for every distinct (id, text); group is the id of the row that stays, copies counts equal rows.

    1. Signatures; rows with equal signatures become one node (exact copies and re-ordered punctuation end here, however many).
    2. Bands of `rows` coordinates; in each bucket the smallest node, the hub, is compared with every other member.  A link needs an agreement of `threshold`.
    3. Members that don't match the hub are compared with all other members, those that match it among them, so every pair of a bucket is linked, connected by
       links, or compared.  A bucket of many members is cut into blocks, and each pair of blocks is a task of its own.
    4. Components of the links.
    """
    signed = written(sign(docs, id_col, text_col, shingle, k).withColumn("mark", F.unhex(F.md5("sig"))), "signatures")
    # numbered where they are written, so a number is a node and no hash
    nodes = written(signed.where("sig is not null").groupBy("mark").agg(F.first("sig").alias("sig")).withColumn("node", F.monotonically_increasing_id()), "nodes")
    width = 4 * rows
    bands = F.array(*[F.xxhash64(F.lit(j), F.substring("sig", 1 + j * width, width)) for j in range(k // rows)])
    members = nodes.select("node", F.explode(bands).alias("bucket"))
    hubs = members.groupBy("bucket").agg(F.min("node").alias("hub"), F.count("*").alias("n")).where("n > 1")
    pairs = written(members.join(hubs, "bucket").where("node != hub").select("bucket", "hub", "node", (F.col("n") - 1).alias("n")), "pairs")
    distinct = pairs.select("hub", "node").distinct()
    scored = distinct.join(nodes.select(F.col("node").alias("hub"), F.col("sig").alias("sig_a")), "hub").join(nodes.select("node", F.col("sig").alias("sig_b")), "node").select("hub", "node", agreement("sig_a", "sig_b").alias("score"))
    scored = written(scored, "scored")
    good = scored.where(F.col("score") >= threshold).select(F.col("hub").alias("a"), F.col("node").alias("b"))
    free = pairs.where("n > 1").join(scored.where(F.col("score") < threshold).select("hub", "node"), ["hub", "node"], "left_semi").select("bucket", "node", F.lit(True).alias("free"))
    free = written(free, "free")
    crowd = pairs.where("n > 1").join(free.select("bucket").distinct(), "bucket", "left_semi").join(free, ["bucket", "node"], "left").select("bucket", "node", "n", F.coalesce("free", F.lit(False)).alias("free"))
    blocks = F.ceil(F.col("n") / block).cast("int")
    crowd = crowd.withColumn("block", F.pmod(F.xxhash64("node"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    crowd = crowd.select("bucket", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "node", "free", "block").join(nodes.select("node", "sig"), "node")
    rest = crowd.groupBy("bucket", "i", "j").applyInPandas(lambda g: linked(g, threshold), "a bigint, b bigint")
    roots = components(good.union(rest.distinct()))
    placed = signed.where("sig is not null").groupBy("rid").agg(F.first("mark").alias("mark"), F.first("id").alias("id"), F.count("*").alias("copies"))
    placed = placed.join(nodes.select("mark", "node"), "mark").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    order = F.struct(F.col("id").isNull().alias("no_id"), F.coalesce("id", F.lit(0)).alias("id"), "rid")
    best = placed.groupBy("root").agg(F.min(order).alias("best"))
    grouped = placed.join(best, "root").select("rid", "id", "copies", F.when(~F.col("best.no_id"), F.col("best.id")).alias("group"), (F.col("rid") == F.col("best.rid")).alias("keep"))
    alone = signed.where("sig is null").groupBy("rid").agg(F.first("id").alias("id"), F.count("*").alias("copies"))
    return grouped.union(alone.select("rid", "id", "copies", F.col("id").alias("group"), F.lit(True).alias("keep")))


def dedup_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **params) -> DataFrame:
    """The rows of docs that stay, all columns as they were.  Rows equal in id and text count as copies; one of them stays."""
    found = near_duplicates(docs, id_col, text_col, **params)
    key = "__cellsieve_rid"
    verdict = found.where("keep").select(F.col("rid").alias(key), F.col("copies").alias("__cellsieve_copies"))
    joined = docs.withColumn(key, row_key(id_col, text_col)).join(verdict, key)
    once = joined.where("__cellsieve_copies = 1")
    more = joined.where("__cellsieve_copies > 1").dropDuplicates([key])
    return once.unionByName(more).select(*docs.columns)
