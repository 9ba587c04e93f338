"""Scans with declared schemas, file streams, and stores for sketches, models and metrics."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession

from gradsift.operators.hashing import HashFamily

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Parquet scan; only columns that a query uses are read.  The files' own schema is kept."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def load_any(spark: SparkSession, path: str, fmt: str, name: str) -> DataFrame:
    """csv, json, orc or parquet with the declared schema of a table."""
    reader = spark.read.format(fmt).schema(SCHEMAS[name])
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def stream_table(spark: SparkSession, path: str, schema, max_files: int = 1) -> DataFrame:
    """File stream of a folder of Parquet files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def write_sketch(cells: DataFrame, fam: HashFamily, path: str, run_id: str) -> None:
    """Cells plus the family that made them, partitioned by run."""
    from pyspark.sql import functions as F

    meta = json.dumps({"rows": fam.rows, "cols": fam.cols, "seed": fam.seed, "field": fam.field})
    cells.withColumns({"run_id": F.lit(run_id), "family": F.lit(meta)}).write.mode("append").partitionBy("run_id").parquet(path)


def read_sketch(spark: SparkSession, path: str, run_id: str) -> tuple[DataFrame, HashFamily]:
    rows = spark.read.parquet(path).where(f"run_id = '{run_id}'")
    found = [r.family for r in rows.select("family").distinct().limit(2).collect()]
    if len(found) != 1:
        raise ValueError(f"{len(found)} hash families in run {run_id}: sketches of different families do not merge")
    return rows.drop("family", "run_id"), HashFamily(**json.loads(found[0]))


def write_model(w: DataFrame, path: str, run_id: str) -> None:
    from pyspark.sql import functions as F

    w.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(path)


def write_metrics(metrics: DataFrame, path: str) -> None:
    """metrics(run_id, seed, t, name, value)."""
    metrics.write.mode("append").partitionBy("run_id").parquet(path)
