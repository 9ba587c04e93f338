"""Streaming operators replayed over ``events``, and functions called from SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from gradsift.functions import udfs
from gradsift.operators import sketch as S
from gradsift.plans.durable import commit, shared_dir
from gradsift.sources import tables
from gradsift.streaming import sketches as ST
from gradsift.workloads import fixtures as X
from gradsift.workloads.fixtures import F4, FAM
from gradsift.workloads.registry import query
from gradsift.workloads.sketch_queries import cells_sql


def replay(spark, d):
    """``events`` as a file stream of a few files in the shared folder."""
    path = f"{shared_dir(spark)}/replay-{uuid.uuid4().hex}"
    ev = tables.load_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    ev.repartitionByRange(4, "ts").write.parquet(path)
    return tables.stream_table(spark, path, ev.schema, max_files=2)


def updates(stream):
    sign = F.when(F.col("event_type") == "error", -1).otherwise(1)
    return stream.select("event_id", "ts", "user_id", F.col("user_id").alias("coord"), (X.cents("value") * sign).alias("delta"))


def drained(spark, frame, mode: str):
    """Runs a stream over all that is there and returns its last result as a table.

    Appended rows are written to files by the executors; only results that are replaced as a whole or row by row are held by the driver.
    """
    name = f"t{uuid.uuid4().hex}"
    if mode == "append":
        path = f"{shared_dir(spark)}/{name}"
        frame.writeStream.format("parquet").option("path", path).outputMode(mode).option("checkpointLocation", f"{shared_dir(spark)}/cp-{name}").trigger(availableNow=True).start().awaitTermination()
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        found = at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)
        return spark.read.schema(frame.schema).parquet(path) if found else spark.createDataFrame([], frame.schema)
    q = frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_dir(spark)}/cp-{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


@query("stream_running_sketch", cells_sql(f"SELECT coord, delta FROM ({F4})"))
def stream_running_sketch(spark, d):
    return drained(spark, ST.stream_sketch(updates(replay(spark, d)), FAM), "complete")


@query(
    "stream_windowed_sketch",
    f"SELECT window_start, row, bucket, CAST(sum(delta * sign) AS BIGINT) AS cell FROM ({FAM.sql_cells(f'''(SELECT date_trunc('day', ts) AS window_start, coord, delta FROM ({F4}))''', keep='window_start, delta')}) GROUP BY window_start, row, bucket",
)
def stream_windowed_sketch(spark, d):
    """One sketch per day, kept by watermark; all windows are read at the end."""
    rows = drained(spark, ST.stream_sketch(updates(replay(spark, d)), FAM, "ts", "1 day", watermark="40 days"), "complete")
    return rows.select(F.col("window.start").alias("window_start"), "row", "bucket", "cell")


SLIDING = f"(SELECT date_trunc('day', ts) - to_days(k.back) AS window_start, coord, delta FROM ({F4}) CROSS JOIN (VALUES (0), (1)) AS k(back))"


@query("stream_sliding_sketch", f"SELECT window_start, row, bucket, CAST(sum(delta * sign) AS BIGINT) AS cell FROM ({FAM.sql_cells(SLIDING, keep='window_start, delta')}) GROUP BY window_start, row, bucket")
def stream_sliding_sketch(spark, d):
    rows = drained(spark, ST.stream_sketch(updates(replay(spark, d)), FAM, "ts", "2 days", "1 day", watermark="40 days"), "complete")
    return rows.select(F.col("window.start").alias("window_start"), "row", "bucket", "cell")


@query(
    "stream_session_sketch",
    f"""SELECT min(ts) AS start, row, bucket, CAST(sum(delta * sign) AS BIGINT) AS cell FROM (SELECT *, sum(fresh) OVER (PARTITION BY row, bucket ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM
    (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY row, bucket ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM ({FAM.sql_cells(f'({F4})', keep='ts, delta')}))) GROUP BY row, bucket, s""",
)
def stream_session_sketch(spark, d):
    return drained(spark, ST.session_sketch(updates(replay(spark, d)), FAM, "ts", "30 minutes", "40 days"), "complete").select(F.col("session_window.start").alias("start"), "row", "bucket", "cell")


@query("stream_static_join", f"SELECT s AS segment, CAST(sum(delta) AS BIGINT) AS delta FROM (SELECT coord % 5 AS s, delta FROM ({F4})) GROUP BY s")
def stream_static_join(spark, d):
    static = spark.range(5).withColumnRenamed("id", "segment")
    joined = updates(replay(spark, d)).join(F.broadcast(static), F.col("coord") % 5 == F.col("segment"))
    return drained(spark, joined.groupBy("segment").agg(F.sum("delta").alias("delta")), "complete")


@query("stream_dedup", "SELECT count(*) AS n FROM events")
def stream_dedup(spark, d):
    """Every event sent twice counts once."""
    s = updates(replay(spark, d))
    twice = ST.once(s.withColumn("again", F.explode(F.array(F.lit(1), F.lit(2)))), "event_id", "ts", "40 days")
    return drained(spark, twice.select("event_id"), "append").agg(F.count("*").alias("n"))


@query(
    "stream_stream_join",
    "SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'error' AND b.event_type <> 'error'",
)
def stream_stream_join(spark, d):
    s = replay(spark, d)
    return drained(spark, ST.follow_ups(s.where("event_type = 'error'"), replay(spark, d).where("event_type <> 'error'"), 30, "40 days"), "append")


@query("stream_fold", cells_sql(f"SELECT coord, delta FROM ({F4})"))
def stream_fold(spark, d):
    """Micro-batch sketches folded into a store keyed by batch id."""
    path = f"{shared_dir(spark)}/fold-{uuid.uuid4().hex}"
    ST.fold_batches(ST.spread(updates(replay(spark, d)), FAM), path, f"{path}-cp").awaitTermination()
    return ST.folded(spark, path)


@query("stream_residuals")
def stream_residuals(spark, d):
    return drained(spark, ST.keep_residuals(updates(replay(spark, d)), 20_000.0), "update")


@query("udtf_sketch_rows", f"SELECT row, bucket, CAST(cell AS DOUBLE) AS cell FROM ({cells_sql(X.f1())})")
def udtf_sketch_rows(spark, d):
    """The table function from SQL, for the updates of all parts, summed per part before."""
    udfs.register_all(spark, FAM)
    X.signed_part_revenue(spark, d).groupBy("coord").agg(F.sum("delta").alias("delta")).createOrReplaceTempView("updates")
    return spark.sql("SELECT s.row, s.bucket, sum(s.cell) AS cell FROM updates, LATERAL sketch_rows(coord, CAST(delta AS DOUBLE)) s GROUP BY s.row, s.bucket")


@query("udaf_sketch_agg", f"SELECT row, bucket, CAST(cell AS DOUBLE) AS cell FROM ({cells_sql(X.f1())})")
def udaf_sketch_agg(spark, d):
    """Packed sketches per worker by the grouped aggregate, unpacked and merged."""
    v = X.signed_part_revenue(spark, d)
    packed = v.groupBy("worker").agg(udfs.sketch_agg(FAM)("coord", F.col("delta").cast("double")).alias("s"))
    flat = packed.select(F.posexplode("s").alias("i", "cell"))
    cells = flat.groupBy((F.col("i") / FAM.cols).cast("int").alias("row"), (F.col("i") % FAM.cols).alias("bucket")).agg(F.sum("cell").alias("cell"))
    touched = S.sketch(v, FAM).select("row", "bucket")
    return cells.join(touched, ["row", "bucket"])


@query("half_precision_cells")
def half_precision_cells(spark, d):
    cells = S.sketch(X.signed_part_revenue(spark, d).withColumn("delta", F.col("delta") / 1e6), FAM)
    return S.dequantise(S.quantise(cells, mode="half")).select("row", "bucket", F.round("cell", 3).alias("cell"))


@query(
    "quantised_cells",
    f"SELECT row, bucket, CAST(round(cell / step) AS SMALLINT) AS code FROM ({cells_sql(X.f1())}) CROSS JOIN (SELECT max(abs(cell)) / 32767.0::DOUBLE AS step FROM ({cells_sql(X.f1())}))",
)
def quantised_cells(spark, d):
    return S.quantise(S.sketch(X.signed_part_revenue(spark, d), FAM)).select("row", "bucket", "code")


@query("format_round_trips", " UNION ALL ".join(f"SELECT '{f}' AS fmt, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events" for f in ("csv", "json", "orc", "parquet")))
def format_round_trips(spark, d):
    out = None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = f"{shared_dir(spark)}/{fmt}-{uuid.uuid4().hex}"
        w = tables.load_table(spark, d, "events").write.format(fmt)
        (w.option("header", True) if fmt == "csv" else w).save(path)
        one = tables.load_any(spark, path, fmt, "events").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids")).select(F.lit(fmt).alias("fmt"), "n", "ids")
        out = one if out is None else out.unionByName(one)
    return out


@query("sketch_store", cells_sql(X.f1()))
def sketch_store(spark, d):
    """Cells written with their hash family and read back."""
    path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    tables.write_sketch(S.sketch(X.signed_part_revenue(spark, d), FAM), FAM, path, "r1")
    cells, fam = tables.read_sketch(spark, path, "r1")
    assert fam == FAM
    return commit(cells, "cells")


@query("tree_merge", cells_sql(X.f1(16)))
def tree_merge(spark, d):
    """Sketches of sixteen workers merged along a spanning tree of a ring with chords."""
    from gradsift.plans import topology as TP

    edges = [(i, (i + 1) % 16) for i in range(16)] + [(i, (i + 5) % 16) for i in range(0, 16, 3)]
    cells = S.sketch(X.signed_part_revenue(spark, d, 16), FAM, by=["worker"])
    return TP.merge_over(cells, TP.spanning_tree(edges, 16))
