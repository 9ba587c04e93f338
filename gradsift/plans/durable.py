"""Versioned intermediates in the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a few numbers that may be broadcast; beyond it the other join is used.
BROADCAST_ROWS = 2_000_000


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; where that is unset, one in the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    return base.rstrip("/") if base else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/intermediate"


def commit(df: DataFrame, name: str) -> DataFrame:
    """Write one version and return its scan: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    found = spark.read.schema(df.schema).parquet(path)
    found._written_to = path
    return found


def release(df: DataFrame | None) -> None:
    """Deletes a committed version that nothing reads any more."""
    if path := getattr(df, "_written_to", None):
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


class Versions:
    """Commits versions of named tables and keeps the last two of each."""

    def __init__(self):
        self.held: dict[str, list[DataFrame]] = {}

    def commit(self, df: DataFrame, name: str) -> DataFrame:
        own = self.held.setdefault(name, [])
        own.append(commit(df, name))
        while len(own) > 2:
            release(own.pop(0))
        return own[-1]

    def close(self, *keep: str) -> None:
        """Releases everything but the last two versions of the tables named."""
        for name, own in self.held.items():
            for df in own if name not in keep else []:
                release(df)


def small(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint if the known number of rows is within the limit."""
    return F.broadcast(df) if rows <= limit else df
