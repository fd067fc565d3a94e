"""Sources, SQL functions, streams, and the contract of __spark_entry__ without the training-data subpackage."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from cellsieve.functions import sql
from cellsieve.operators import cells, mining
from cellsieve.sources import tables
from cellsieve.streaming import transactions as st

ROOT = Path(__file__).resolve().parent.parent


def test_text_transactions(spark, tmp_path):
    (tmp_path / "t.dat").write_text("1 2 3\n\n3 3 1\n7\n")
    got = tables.read_transactions_text(spark, str(tmp_path / "t.dat"))
    assert sorted(r["items"] for r in got.collect()) == [[1, 2, 3], [1, 3], [7]]
    tables.write_transactions_text(got, str(tmp_path / "out"))
    assert tables.read_transactions_text(spark, str(tmp_path / "out")).count() == 3


def test_functions(spark):
    df = spark.createDataFrame([([0, 2, 5], 0b100101, 0b100, ["a", "b"], ["b", "c"])], "r array<int>, m bigint, k bigint, x array<string>, y array<string>")
    assert tuple(df.select(sql.pattern_mask("r"), sql.parity(F.col("m"), F.col("k")), F.round(sql.jaccard("x", "y"), 4)).first()) == (37, 1, 0.3333)
    q = sql.black_box_quality(lambda n, f, p: n * f - p)
    assert df.select(q(F.lit(2), F.lit(10), F.lit(3))).first()[0] == 17


def test_table_functions(spark):
    sql.register(spark)
    rows = [(x,) for x in ["a,b,c", "a,b", "b,c", "a,c", "c", "a,b,c,d"] * 4]
    spark.createDataFrame(rows, "items string").createOrReplaceTempView("baskets")
    got = spark.sql("SELECT * FROM sample_patterns(TABLE(baskets) WITH SINGLE PARTITION, 0.3, 0.9, 25, 'freq')").collect()
    assert len(got) == 25 and {r["status"] for r in got} == {"ok"} and {r["pattern"] for r in got} <= {"a", "b", "c", "a,b", "a,c", "b,c", "a,b,c"}
    total = spark.sql("SELECT * FROM estimate_patterns(TABLE(baskets) WITH SINGLE PARTITION, 0.3, 0.9, 0, 'uniform')").first()[0]
    assert total == 7.0


def test_sample_source(spark, tmp_path):
    spark.createDataFrame([("a", 3), ("b", 1)], "pattern string, w bigint").coalesce(1).write.parquet(str(tmp_path / "p"))
    spark.dataSource.register(st.PatternSamples)
    one = spark.read.format("pattern_samples").options(path=str(tmp_path / "p"), n=200, partitions=3).load().collect()
    two = spark.read.format("pattern_samples").options(path=str(tmp_path / "p"), n=200, partitions=1).load().collect()
    assert sorted(one) == sorted(two) and len(one) == 200 and 100 < sum(r["pattern"] == "a" for r in one) < 190


def events(spark, tmp_path):
    """Four days of events in four files, two files that move the watermark, then an event that is far too late.

    Spark drops rows by the watermark of the batch before the last, so one file would not be enough."""
    folder = tmp_path / "events"
    rows = [(d * 10 + k, f"2024-01-0{d + 1} 0{k}:00:00", k % 2, ["view", "buy", "cart"][k % 3], 1.0, "{}") for d in range(4) for k in range(6)]
    rows += [(100, "2024-01-20 00:00:00", 0, "view", 1.0, "{}"), (102, "2024-01-20 01:00:00", 0, "view", 1.0, "{}"), (101, "2024-01-02 03:00:00", 0, "late", 1.0, "{}")]
    parts = [rows[i : i + 6] for i in range(0, 24, 6)] + [[r] for r in rows[24:]]
    for i, p in enumerate(parts):
        df = spark.createDataFrame(p, "event_id bigint, ts string, user_id bigint, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        df.coalesce(1).write.mode("append").parquet(str(folder))
    import os
    import time

    for k, f in enumerate(sorted(folder.glob("*.parquet"), key=lambda f: f.stat().st_mtime_ns)):
        os.utime(f, (time.time() - 1000 + k, time.time() - 1000 + k))
    return str(folder)


def drained(df, mode, name):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    return df.sparkSession.table(name)


def test_streams(spark, tmp_path):
    folder = events(spark, tmp_path)
    stream = st.event_stream(spark, folder)
    got = {(str(r["start"])[:10], r["user_id"]): r["items"] for r in drained(st.windowed_transactions(stream), "append", "days").collect()}
    batch = spark.read.parquet(folder).where("event_type != 'late' and event_id < 100").groupBy(F.to_date("ts").cast("string").alias("d"), "user_id").agg(F.array_sort(F.collect_set(F.concat(F.lit("type="), F.col("event_type")))).alias("items"))
    assert got == {(r["d"], r["user_id"]): r["items"] for r in batch.collect()}
    assert drained(st.deduplicated(stream), "append", "dedup").count() == 26
    tracked = spark.createDataFrame([("type=buy", ["type=buy"]), ("type=view", ["type=view"])], "pattern string, items array<string>")
    out = drained(st.tracked_supports(stream.select(F.array(F.concat(F.lit("type="), F.col("event_type"))).alias("items")), tracked), "complete", "tracked")
    assert {r["pattern"]: r["support"] for r in out.collect()} == {"type=buy": 8, "type=view": 10}
    assert drained(st.session_transactions(stream, "2 hours"), "append", "sessions").count() > 0


def test_resampling_each_batch(spark, tmp_path):
    folder = events(spark, tmp_path)
    seen = []
    tx = st.windowed_transactions(st.event_stream(spark, folder))
    run = st.resample_batches(1, 3, "uniform", cells.Scaled(1.0, 1.0), 5, lambda df, b: seen.extend(df.collect()))
    q = tx.writeStream.foreachBatch(run).outputMode("append").start()
    q.processAllAvailable()
    q.stop()
    assert seen and {r["status"] for r in seen} == {"ok"}


def test_mining_of_nothing(spark):
    empty = spark.createDataFrame([], "tid bigint, items array<string>, label boolean")
    assert mining.dataset_stats(empty).first()["transactions"] in (0, None)


def test_entry_without_the_training_data_subpackage(tmp_path):
    """In a copy without the subpackage, its tests and the pipeline."""
    for what in ("cellsieve", "tests"):
        shutil.copytree(ROOT / what, tmp_path / what, ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e\nassert 'cell_sample_freq' in e.queries() and not any(q.startswith('op') for q in e.queries()) and 'pipeline' not in e.queries()\nassert set(e.oracle_sql()) <= set(e.queries())"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=env)


def test_no_local_checkpoint_folder_on_a_cluster(spark):
    from types import SimpleNamespace

    from cellsieve.functions import lineage

    context = SimpleNamespace(getCheckpointDir=lambda: None, master="spark://host:7077")
    session = SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda *_: None))
    with pytest.raises(ValueError):
        lineage.cut(SimpleNamespace(sparkSession=session))
