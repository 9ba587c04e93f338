"""Shared helpers: durable intermediate tables, checked broadcasts, components, tables.

Intermediate results that several jobs read are written as Parquet below the session's
``spark.checkpoint.dir``, which every executor shares; a lost executor therefore never
loses them.  Where that setting is unset they go below the warehouse folder, which is
shared as well.  ``discard`` removes those that nothing reads any more.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of two or three longs that may be broadcast; beyond it the join is shuffled.
BROADCAST_ROWS = 1_000_000


def shared_dir(spark: SparkSession) -> str:
    """Folder for durable intermediates: the session's checkpoint folder, else one in the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    return base.rstrip("/") if base else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/intermediate"


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


#: Spark deletes the shuffle files of a query as it ends, not when the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and return a scan of it (cuts the lineage); its shuffle files go at once."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    found = spark.read.schema(df.schema).parquet(path)
    found._written_to = path
    return found


def discard(*frames: DataFrame) -> None:
    """Deletes materialised tables whose readers have all been written themselves."""
    for df in frames:
        if path := getattr(df, "_written_to", None):
            spark = df.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def maybe_broadcast(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint only when the counted rows are within the limit."""
    return F.broadcast(df) if rows <= limit else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of an undirected edge list (u, v); component = smallest node.

    Alternating star contraction: every round hangs larger neighbours on the smallest one
    (large star), then hangs lower neighbours on it (small star), until the edges no longer
    change.  Minima are aggregated before the join and both join sides are plain scans, so
    adaptive execution may split the rows of a hot centre.
    """
    e = materialise(
        edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct(), "cc"
    )
    state = None
    while True:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("low")), "cc-low")
        big = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v"))
        big = materialise(big.where("u > v").distinct(), "cc-big")
        least = materialise(big.groupBy("u").agg(F.min("v").alias("low")), "cc-low")
        after = (
            big.join(least, "u")
            .select(F.explode(F.array(F.struct("v", "low"), F.struct(F.col("u").alias("v"), "low"))).alias("p"))
            .select(F.col("p.v").alias("u"), F.col("p.low").alias("v"))
            .where("u > v")
            .distinct()
        )
        after = materialise(after, "cc")
        discard(e, low, big, least)
        e = after
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    members = e.groupBy("u").agg(F.min("v").alias("component")).withColumnRenamed("u", "node")
    members = materialise(members.unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()), "components")
    discard(e)
    return members
