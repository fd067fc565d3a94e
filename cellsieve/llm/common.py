"""Helpers shared by the training-data operators: tables, working folders, 64-bit mixing, text chunks."""

from __future__ import annotations

import bisect
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

U64 = np.uint64
GOLDEN = U64(0x9E3779B97F4A7C15)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: the session's checkpoint folder.  Only where none is set and all runs on one machine
    (tests) a temporary folder becomes the checkpoint folder; on a cluster without one this raises."""
    found = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="cellsieve-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(found)
    return found


def work_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, what: str) -> DataFrame:
    """Writes df as Parquet in the shared folder and reads it back; column types stay."""
    path = work_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def mix64(x: np.ndarray) -> np.ndarray:
    """The splitmix finaliser, on a new uint64 array."""
    x = x ^ (x >> U64(30))
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def times(n: int) -> np.uint64:
    """n steps of the golden sequence, modulo 2**64."""
    return U64(n * int(GOLDEN) & 0xFFFFFFFFFFFFFFFF)


def unit(x: np.ndarray) -> np.ndarray:
    """Uniform doubles in (0, 1) from the high 53 bits."""
    return ((x >> U64(11)).astype(np.float64) + 0.5) * (2.0**-53)


def chunks(batch: pa.RecordBatch, column: str, rows: int = 512, chars: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    """Slices of a batch that hold at most so many rows, and so many bytes of the column unless a single row is longer."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    start, held = 0, 0
    for i, n in enumerate(sizes):
        if i > start and (held + n > chars or i - start >= rows):
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)


def lowered(text: str) -> str:
    """Lower case with the same offsets: characters whose lower case is longer stay."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(x if len(x) == 1 else c for c in text for x in [c.lower()])


class Taken:
    """Disjoint stretches [start, stop), kept in order, so that a new one is placed or refused by bisection."""

    def __init__(self) -> None:
        self.starts: list[int] = []
        self.stops: list[int] = []

    def add(self, start: int, stop: int) -> bool:
        """Whether [start, stop) overlapped nothing and was added."""
        at = bisect.bisect_right(self.starts, start)
        if at and self.stops[at - 1] > start or at < len(self.starts) and self.starts[at] < stop:
            return False
        self.starts.insert(at, start)
        self.stops.insert(at, stop)
        return True


def disjoint(spans: Iterable[tuple], start: int, stop: int) -> list[tuple]:
    """Of spans in order of preference, those that overlap no earlier choice; start and stop are their places in the tuples."""
    taken = Taken()
    return [s for s in spans if taken.add(s[start], s[stop])]
