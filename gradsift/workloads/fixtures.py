"""Update streams and example sets derived from the given tables, with the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.operators.hashing import HashFamily
from gradsift.sources.tables import load_table

#: The sketch of all queries that an SQL engine checks.
FAM = HashFamily(rows=5, cols=256, seed=42)


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


def signed_part_revenue(spark: SparkSession, d: str, workers: int = 4) -> DataFrame:
    """Revenue per part in cents; returned lines are negative."""
    sign = F.when(F.col("l_returnflag") == "R", -1).otherwise(1)
    return load_table(spark, d, "lineitem").select(
        (F.col("l_orderkey") % workers).cast("int").alias("worker"), F.col("l_partkey").alias("coord"), (cents("l_extendedprice") * sign).alias("delta")
    )


def f1(workers: int = 4) -> str:
    return (
        f"SELECT CAST(l_orderkey % {workers} AS INTEGER) AS worker, l_partkey AS coord, "
        "CAST(round(l_extendedprice * 100) AS BIGINT) * (CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END) AS delta FROM lineitem"
    )


def planted_part_revenue(spark: SparkSession, d: str, workers: int = 4) -> DataFrame:
    """The same with every 97th part a thousand times heavier."""
    return signed_part_revenue(spark, d, workers).withColumn("delta", F.when(F.col("coord") % 97 == 0, F.col("delta") * 1000).otherwise(F.col("delta")))


def f2(workers: int = 4) -> str:
    return f"SELECT worker, coord, CASE WHEN coord % 97 = 0 THEN delta * 1000 ELSE delta END AS delta FROM ({f1(workers)})"


def customer_spend(spark: SparkSession, d: str, workers: int = 4) -> DataFrame:
    return load_table(spark, d, "orders").select(
        (F.col("o_orderkey") % workers).cast("int").alias("worker"), F.col("o_custkey").alias("coord"), cents("o_totalprice").alias("delta")
    )


def f3(workers: int = 4) -> str:
    return f"SELECT CAST(o_orderkey % {workers} AS INTEGER) AS worker, o_custkey AS coord, CAST(round(o_totalprice * 100) AS BIGINT) AS delta FROM orders"


def event_updates(spark: SparkSession, d: str) -> DataFrame:
    """Signed event values per user and per JSON key; errors are negative."""
    sign = F.when(F.col("event_type") == "error", -1).otherwise(1)
    return load_table(spark, d, "events").select(
        "event_id", "ts", F.col("user_id").alias("coord"), F.from_json("props", "k long")["k"].alias("k"), (cents("value") * sign).alias("delta")
    )


F4 = (
    "SELECT event_id, ts, user_id AS coord, CAST(json_extract(props, '$.k') AS BIGINT) AS k, "
    "CAST(round(value * 100) AS BIGINT) * (CASE WHEN event_type = 'error' THEN -1 ELSE 1 END) AS delta FROM events"
)


def parts(spark: SparkSession, d: str) -> int:
    """Size of part-keyed vectors: keys are 0 to the number of parts less one."""
    return load_table(spark, d, "part").count()


# examples ---------------------------------------------------------------------

#: Planted coefficients of the regression examples (coordinate 0 is the constant).
PLANTED = [1.0, -2.0, 0.5, 3.0, -1.0, 2.0, 0.25, -0.75]
DIM = len(PLANTED)


def order_features(spark: SparkSession, d: str) -> DataFrame:
    """ex_id, x0..x7, y: orders with aggregates of their lines (left join), target planted plus noise."""
    o, li, p = (load_table(spark, d, t) for t in ("orders", "lineitem", "part"))
    lines = li.join(p.select(F.col("p_partkey").alias("l_partkey"), "p_size"), "l_partkey")
    agg = lines.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(
        F.count("*").alias("n"),
        F.sum(F.col("l_quantity").cast("long")).alias("q"),
        F.sum(F.when(F.col("l_returnflag") == "R", 1).otherwise(0)).alias("r"),
        F.sum(F.round(F.col("l_discount") * 100).cast("long")).alias("disc"),
        F.sum("p_size").alias("size"),
    )
    j = o.join(agg, "o_orderkey", "left").fillna(0, ["n", "q", "r", "disc", "size"])
    n = F.greatest(F.col("n"), F.lit(1))
    x = [
        F.lit(1.0),
        F.col("n") / 8.0,
        F.col("q") / (n * 50.0),
        F.col("disc") / (n * 10.0),
        F.col("r") / (n * 1.0),
        F.col("size") / (n * 50.0),
        F.col("o_totalprice") / 500000.0,
        F.substring("o_orderpriority", 1, 1).cast("int") / 5.0,
    ]
    noise = (F.col("o_orderkey") * 7919 % 101 - 50) / 500.0
    out = j.select(F.col("o_orderkey").alias("ex_id"), *(c.cast("double").alias(f"x{i}") for i, c in enumerate(x)), noise.alias("noise"))
    y = F.col("noise")
    for i, c in enumerate(PLANTED):
        y = y + F.col(f"x{i}") * F.lit(c)
    return out.select("ex_id", *(f"x{i}" for i in range(DIM)), y.alias("y"))


def ridge_examples(spark: SparkSession, d: str, workers: int = 4) -> DataFrame:
    """ex_id, worker, y, x as array of (coord, val)."""
    x = F.array(*(F.struct(F.lit(i).cast("long").alias("coord"), F.col(f"x{i}").alias("val")) for i in range(DIM)))
    return order_features(spark, d).select("ex_id", (F.col("ex_id") % workers).cast("int").alias("worker"), "y", x.alias("x"))


ORDER_FEATURES_SQL = f"""
SELECT ex_id, {", ".join(f"x{i}" for i in range(DIM))}, noise{"".join(f" + x{i} * ({c}::DOUBLE)" for i, c in enumerate(PLANTED))} AS y FROM (
 SELECT o_orderkey AS ex_id, 1.0::DOUBLE AS x0, n / 8.0::DOUBLE AS x1, q / (m * 50.0::DOUBLE) AS x2,
  disc / (m * 10.0::DOUBLE) AS x3, r / (m * 1.0::DOUBLE) AS x4, size / (m * 50.0::DOUBLE) AS x5,
  o_totalprice / 500000.0::DOUBLE AS x6, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) / 5.0::DOUBLE AS x7,
  (o_orderkey * 7919 % 101 - 50) / 500.0::DOUBLE AS noise
 FROM (
  SELECT o.*, coalesce(a.n, 0)::DOUBLE AS n, coalesce(a.q, 0)::DOUBLE AS q, coalesce(a.r, 0)::DOUBLE AS r, coalesce(a.disc, 0)::DOUBLE AS disc,
   coalesce(a.size, 0)::DOUBLE AS size, greatest(coalesce(a.n, 0), 1)::DOUBLE AS m
  FROM orders o LEFT JOIN (
   SELECT l_orderkey, count(*) AS n, sum(CAST(l_quantity AS BIGINT)) AS q, sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS r,
    sum(CAST(round(l_discount * 100) AS BIGINT)) AS disc, sum(p_size) AS size
   FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_orderkey
  ) a ON o.o_orderkey = a.l_orderkey))
"""


def ridge_long_sql(workers: int = 4) -> str:
    """ex_id, worker, y, coord, val: one row per entry."""
    return " UNION ALL ".join(f"SELECT ex_id, CAST(ex_id % {workers} AS INTEGER) AS worker, y, {i}::BIGINT AS coord, x{i} AS val FROM ({ORDER_FEATURES_SQL})" for i in range(DIM))
