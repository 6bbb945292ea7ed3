"""Streams against their batch form, late rows, repeats, and that nothing outside needs the training-data package."""

import shutil
import subprocess
import sys
from datetime import datetime
from pathlib import Path

from pyspark.sql import functions as F

from objann.plans import relational
from objann.sources.tables import load_table
from objann.streaming import events

ROOT = Path(__file__).resolve().parents[1]
SF = "/root/testdata/sf0.001"


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    stamp = lambda h: datetime(2024, 1, 1, h)
    batches = [[(1, stamp(1), 1, "view", 1.0, "{}"), (2, stamp(9), 1, "view", 1.0, "{}")], [(3, stamp(2), 1, "view", 1.0, "{}"), (4, stamp(10), 2, "view", 1.0, "{}")], [(5, stamp(3), 1, "view", 1.0, "{}")]]
    (tmp_path / "in").mkdir()
    source = spark.readStream.schema(events.EVENT_SCHEMA).parquet(str(tmp_path / "in"))
    counted = events.tumbling_counts(source)
    seen, dropped = {}, 0
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, events.EVENT_SCHEMA).coalesce(1).write.parquet(str(tmp_path / f"raw{k}"))
        shutil.copy(next((tmp_path / f"raw{k}").glob("part-*.parquet")), tmp_path / "in" / f"{k}.parquet")
        query = counted.writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "checkpoint")).foreachBatch(lambda b, n: seen.update({(r.start.hour, r.event_type): r.n for r in b.collect()})).trigger(availableNow=True).start()
        query.awaitTermination()
        dropped += events.late_rows(query)
    assert seen == {(1, "view"): 1, (9, "view"): 1, (10, "view"): 1} and dropped == 2


def test_repeats_within_the_watermark_go(spark, tmp_path):
    df = load_table(spark, SF, "events").limit(50)
    (tmp_path / "in").mkdir()
    df.union(df).coalesce(1).write.parquet(str(tmp_path / "raw"))
    shutil.copy(next((tmp_path / "raw").glob("part-*.parquet")), tmp_path / "in" / "events.parquet")
    out, found = events.without_repeats(events.event_stream(spark, str(tmp_path / "in"))), []
    out.writeStream.option("checkpointLocation", str(tmp_path / "c")).foreachBatch(lambda b, n: found.extend(r.event_id for r in b.select("event_id").collect())).trigger(availableNow=True).start().awaitTermination()
    assert sorted(found) == sorted(r.event_id for r in df.select("event_id").collect())


def test_running_sizes_equal_the_batch(spark):
    want = {r.user_id: r.n for r in load_table(spark, SF, "events").groupBy("user_id").agg(F.count("*").alias("n")).collect()}
    assert {r.object_id: r.n_points for r in events.stream_state(spark, SF).collect()} == want


def test_append_mode_holds_closed_windows_only(spark):
    whole = {(r.start, r.event_type): r.n for r in events.tumbling_counts(load_table(spark, SF, "events")).collect()}
    closed = {(r.start, r.event_type): r.n for r in events.stream_windows(spark, SF, "append").collect()}
    assert closed.items() <= whole.items()


def test_one_text_runs_in_both_engines(spark):
    assert relational.run_text(spark, SF, relational.TEXTS["join_cross"]).count() == 125
    assert "{" not in relational.duckdb_text(relational.TEXTS["global_top_k"])


def test_the_library_stands_without_the_training_data_package(tmp_path):
    for name in ("objann", "__spark_entry__.py"):
        source = ROOT / name
        shutil.copytree(source, tmp_path / name) if source.is_dir() else shutil.copy(source, tmp_path / name)
    shutil.rmtree(tmp_path / "objann" / "llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 100 and not any(n.startswith('op') for n in q) and set(o) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
