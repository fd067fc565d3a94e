"""Streams of transactions (S1-S10): windows of events become transactions, supports and samples follow them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

from ..operators import cells, mining


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events of a folder of Parquet files as a stream; ts becomes a timestamp, which watermarks need."""
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_transactions(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "2 days") -> DataFrame:
    """(start, user_id, items): what a user did in each tumbling or sliding window; rows behind the watermark are dropped."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    tx = events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.array_sort(F.collect_set(F.concat(F.lit("type="), F.col("event_type")))).alias("items"))
    return tx.select(F.col("w.start").alias("start"), "user_id", "items")


def session_transactions(events: DataFrame, gap: str = "30 minutes", late: str = "2 days") -> DataFrame:
    tx = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.array_sort(F.collect_set(F.concat(F.lit("type="), F.col("event_type")))).alias("items"))
    return tx.select(F.col("w.start").alias("start"), "user_id", "items")


def tracked_supports(tx: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern, support) of a fixed, small set of patterns, growing with the stream; for update mode."""
    held = F.broadcast(patterns.select("pattern", F.col("items").alias("wanted")))
    return tx.join(held, F.size(F.array_except("wanted", "items")) == 0).groupBy("pattern").agg(F.count("*").alias("support"))


def deduplicated(events: DataFrame, late: str = "2 days") -> DataFrame:
    """Events whose id was seen inside the watermark are dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def followed(first: DataFrame, second: DataFrame, within: str = "1 hour", late: str = "2 days") -> DataFrame:
    """(user_id, ts, later): events of the second stream within a time after one of the first, of the same user."""
    a = first.withWatermark("ts", late).select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = second.withWatermark("ts", late).select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"ua = ub AND tb >= ta AND tb <= ta + INTERVAL {within}")).select(F.col("ua").alias("user_id"), F.col("ta").alias("ts"), F.col("tb").alias("later"))


def resample_batches(minsup: int, max_len: int, quality: str, scaled: cells.Scaled, n: int, sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function (S5): each batch of transactions is mined and sampled anew; the sink gets the samples."""

    def run(tx: DataFrame, batch: int) -> None:
        rows = tx.select(F.xxhash64("user_id", "items").alias("tid"), "items", F.lit(None).cast("boolean").alias("label")).persist()
        patterns = mining.frequent_levelwise(rows, minsup, max_len).persist()
        total = cells.weighted(patterns, quality).agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]
        if total:
            sink(cells.sample(patterns, quality, scaled, float(total), n, 0.9, seed=1000 + batch), batch)
        patterns.unpersist()
        rows.unpersist()

    return run


class Reservoir(StatefulProcessor):
    """The `size` transactions of each key with the smallest hash draws: a uniform sample that any order of arrival gives alike."""

    def __init__(self, size: int = 5) -> None:
        self.size = size

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getValueState("held", "rows array<struct<u bigint, items string>>")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802
        from ..functions.hashing import draw_py

        held = [(r[0], r[1]) for r in self.held.get()[0]] if self.held.exists() else []
        for pdf in rows:
            held += [(draw_py("reservoir", key[0], s, i), i) for s, i in zip(pdf["start"].astype(str), pdf["items"])]
        held = sorted(set(held))[: self.size]
        self.held.update((held,))
        yield pd.DataFrame({"user_id": [key[0]] * len(held), "items": [i for _, i in held]})

    def close(self) -> None:
        pass


def reservoirs(tx: DataFrame, size: int = 5) -> DataFrame:
    slim = tx.select("user_id", F.col("start").cast("string").alias("start"), F.array_join("items", ",").alias("items"))
    return slim.groupBy("user_id").transformWithStateInPandas(Reservoir(size), "user_id bigint, items string", "Update", "None")


class PatternSamples(DataSource):
    """Data source `pattern_samples`: draws from a stored distribution, by ranges of sample numbers in batch (O3), or a batch a trigger as a stream.

    Options: path, a Parquet folder with pattern and w; n; seed; batch.  Reading is anytime: sample k is the same whenever it is read."""

    @classmethod
    def name(cls) -> str:
        return "pattern_samples"

    def schema(self) -> str:
        return "sample_id bigint, pattern string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return SampleReader(self.options)

    def simpleStreamReader(self, schema: StructType) -> SimpleDataSourceStreamReader:  # noqa: N802
        return SampleStream(self.options)


class Drawer:
    def __init__(self, options: dict) -> None:
        self.path, self.seed = options["path"], options.get("seed", "42")

    def draw(self, start: int, stop: int) -> Iterator[tuple[int, str]]:
        import bisect

        import pyarrow.parquet as pq

        from ..functions.hashing import draw_py

        t = pq.read_table(self.path, columns=["pattern", "w"]).to_pandas().sort_values("pattern")
        ends, names = t["w"].cumsum().tolist(), t["pattern"].tolist()
        for k in range(start, stop):
            if ends:
                yield k, names[bisect.bisect_right(ends, draw_py(self.seed, "source", k) % ends[-1])]


class SampleReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.drawer, self.n, self.parts = Drawer(options), int(options.get("n", 100)), int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((self.n * i // self.parts, self.n * (i + 1) // self.parts)) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from self.drawer.draw(*partition.value)


class SampleStream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict) -> None:
        self.drawer, self.batch = Drawer(options), int(options.get("batch", 50))

    def initialOffset(self) -> dict:  # noqa: N802
        return {"next": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        stop = start["next"] + self.batch
        return self.drawer.draw(start["next"], stop), {"next": stop}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        return self.drawer.draw(start["next"], end["next"])

    def commit(self, end: dict) -> None:
        pass
