import datetime as dt
import time

from pyspark.sql import functions as F

from gradsift.operators import sketch as S
from gradsift.operators.hashing import HashFamily
from gradsift.sources.tables import stream_table
from gradsift.streaming import sketches as ST
from gradsift.workloads.stream_queries import drained

FAM = HashFamily(3, 8, 1)
SCHEMA = "event_id long, ts timestamp, coord long, delta long"


def write(spark, rows, path):
    """One file of one batch; modification times order the files of a stream."""
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(path)
    time.sleep(1.1)


def day(n, hour=0):
    return dt.datetime(2024, 1, n, hour)


def test_late_rows_are_dropped_and_closed_windows_come_once(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    write(spark, [(1, day(1), 3, 5), (2, day(10), 4, 7)], path)
    write(spark, [(4, day(10, 5), 4, 1)], path)
    write(spark, [(3, day(2), 3, 1000), (5, day(20), 1, 1)], path)  # event 3 is eight days late, as the batch before says
    got = drained(spark, ST.stream_sketch(stream_table(spark, path, SCHEMA), FAM, "ts", "1 day", watermark="1 day"), "append")
    got = {(r.window.start.day, r.row, r.bucket): r.cell for r in got.collect()}
    batch = spark.createDataFrame([(1, 3, 5), (10, 4, 7), (10, 4, 1)], "d int, coord long, delta long")
    want = {(r.d, r.row, r.bucket): r.cell for r in S.sketch(batch, FAM, by=["d"]).collect()}
    assert got == want  # the window of day 20 is still open


def test_a_replayed_batch_changes_nothing(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    write(spark, [(i, day(1), i % 5, i) for i in range(20)], path)
    cells = ST.spread(stream_table(spark, path, SCHEMA), FAM)
    for checkpoint in ("a", "a", "b"):  # again with its checkpoint, and after the checkpoint was lost
        ST.fold_batches(cells, f"file://{tmp_path}/store", f"file://{tmp_path}/cp-{checkpoint}").awaitTermination()
    want = {(r.row, r.bucket): r.cell for r in S.sketch(spark.read.parquet(path), FAM).collect()}
    assert {(r.row, r.bucket): r.cell for r in ST.folded(spark, f"file://{tmp_path}/store").collect()} == want


def test_residuals_by_threshold_and_by_time_out(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    write(spark, [(1, day(1), 1, 60), (2, day(1), 2, 5)], path)
    write(spark, [(3, day(1), 1, 50)], path)
    frame = ST.keep_residuals(stream_table(spark, path, SCHEMA), 100.0, timeout_ms=1000)
    q = frame.writeStream.format("memory").queryName("residuals").outputMode("update").option("checkpointLocation", f"file://{tmp_path}/cp").trigger(processingTime="200 milliseconds").start()
    rows = set()
    for _ in range(90):
        time.sleep(1)
        rows = {tuple(r) for r in spark.table("residuals").collect()}
        if len(rows) >= 2 and any(r[0] == 2 for r in rows):
            break
    q.stop()
    assert (2, 5.0, "timeout") in rows and sum(r[1] for r in rows if r[0] == 1) == 110.0


def test_duplicates_within_the_watermark(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    write(spark, [(1, day(1), 1, 1), (2, day(1), 1, 1)], path)
    write(spark, [(1, day(1), 1, 1), (3, day(1), 1, 1)], path)
    got = drained(spark, ST.once(stream_table(spark, path, SCHEMA), "event_id", "ts", "5 days").select("event_id"), "append")
    assert sorted(r.event_id for r in got.collect()) == [1, 2, 3] and got.agg(F.count("*")).first()[0] == 3


def test_appended_rows_are_not_held_by_the_driver(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    spark.range(1000).selectExpr("id as event_id", "timestamp'2024-01-01' as ts", "id as coord", "id as delta").write.parquet(path)
    got = drained(spark, ST.once(stream_table(spark, path, SCHEMA), "event_id", "ts", "5 days").select("event_id"), "append")
    assert got.count() == 1000 and "LocalTableScan" not in got._jdf.queryExecution().optimizedPlan().toString() and got.inputFiles()
    empty = spark.createDataFrame([], SCHEMA)
    empty.write.parquet(f"file://{tmp_path}/none")
    none = drained(spark, ST.once(stream_table(spark, f"file://{tmp_path}/none", SCHEMA), "event_id", "ts", "5 days").select("event_id"), "append")
    assert none.count() == 0 and none.columns == ["event_id"]
