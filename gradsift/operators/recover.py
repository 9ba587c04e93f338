"""Recovery of large coordinates from a merged sketch, and contraction operators.

All picks are deterministic: estimates order by magnitude and coordinate, random picks by a seeded
hash of (seed, step, coordinate).  Exact values come from a second round: picked ids are at most
P * k and are broadcast; every worker answers with its own values, which are summed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.operators.hashing import FIELD, HashFamily
from gradsift.operators.sketch import by_size, estimate_all, norm2
from gradsift.plans.durable import small


def shuffle_key(coord: Column, seed: int, t: int = 0) -> Column:
    """Seeded pseudo-random order of coordinates by integer arithmetic (the same in any engine)."""
    a, b = (seed * 2_654_435 + 40_503) % FIELD, (t * 97_531 + seed * 131 + 12_345) % FIELD
    x = (coord * F.lit(a).cast("long") + F.lit(b).cast("long")) % F.lit(FIELD).cast("long")
    return (x * x % F.lit(FIELD).cast("long") * (x % 65_521 + 1)) % F.lit(FIELD).cast("long")


def sql_shuffle_key(coord: str, seed: int, t: int = 0) -> str:
    a, b = (seed * 2_654_435 + 40_503) % FIELD, (t * 97_531 + seed * 131 + 12_345) % FIELD
    x = f"(({coord} * {a}::BIGINT + {b}) % {FIELD})"
    return f"(({x} * {x} % {FIELD} * ({x} % 65521 + 1)) % {FIELD})"


def exact_refetch(vector: DataFrame, picks: DataFrame, count: int, reduce: str = "sum", workers: int = 1) -> DataFrame:
    """(coord, exact) of the picked coordinates; zero where no worker holds one."""
    ids = small(picks.select("coord"), count)
    own = vector.join(ids, "coord", "left_semi").groupBy("coord").agg(F.sum("delta").alias("exact"))
    out = picks.join(own, "coord", "left").withColumn("exact", F.coalesce("exact", F.lit(0)))
    return out.withColumn("exact", F.col("exact") / F.lit(float(workers))) if reduce == "mean" else out


def heavy_or_random_picks(cells: DataFrame, fam: HashFamily, d: int, k: int, seed: int, t: int = 0, overflow: str = "largest") -> DataFrame:
    """(coord, is_heavy): coordinates whose *squared* estimate reaches norm/k, filled up to k at random.

    If more than k are heavy: ``largest`` keeps the k largest estimates, ``random`` k of them in
    seeded order, ``keep_all`` all.  A zero sketch picks nothing.
    """
    est = estimate_all(cells, fam, d).crossJoin(F.broadcast(norm2(cells)))
    est = est.where(F.col("norm2") > 0)
    heavy = F.col("est") * F.col("est") >= F.col("norm2") / F.lit(k)
    est = est.select("coord", "est", heavy.alias("is_heavy"), shuffle_key(F.col("coord"), seed, t).alias("key"))
    chosen = {"largest": [F.col("is_heavy").desc(), F.when(F.col("is_heavy"), F.abs("est")).desc_nulls_last()], "random": [F.col("is_heavy").desc()], "keep_all": [F.col("is_heavy").desc()]}[overflow]
    if overflow == "keep_all":
        rest = est.where(~F.col("is_heavy")).orderBy("key", "coord").limit(k)
        count = est.agg(F.count_if("is_heavy").alias("heavies"))
        order = Window.orderBy("key", "coord")  # at most k rows
        rest = rest.withColumn("n", F.row_number().over(order)).crossJoin(F.broadcast(count)).where(F.col("n") <= k - F.col("heavies"))
        return est.where("is_heavy").select("coord", "is_heavy").unionByName(rest.select("coord", "is_heavy"))
    return est.orderBy(*chosen, "key", "coord").limit(k).select("coord", "is_heavy")


def recover_heavy_or_random(cells, fam, d, k, vector, seed=0, t=0, overflow="largest", reduce="sum", workers=1) -> DataFrame:
    """(coord, is_heavy, exact) of the picks; everything else counts as zero."""
    return exact_refetch(vector, heavy_or_random_picks(cells, fam, d, k, seed, t, overflow), d if overflow == "keep_all" else k, reduce, workers)


def recover_over_ask(cells, fam, d, k, p, vector, reduce="sum", workers=1, refetch=True) -> DataFrame:
    """Best k by exact value of the p * k largest estimates (``refetch=False``: k largest estimates)."""
    est = estimate_all(cells, fam, d)
    if not refetch:
        return est.orderBy(*by_size("est")).limit(k).select("coord", F.col("est").alias("exact"))
    asked = est.orderBy(*by_size("est")).limit(p * k).select("coord")
    return exact_refetch(vector, asked, p * k, reduce, workers).orderBy(*by_size("exact")).limit(k)


def random_coords(spark, d: int, n: int, seed: int, t: int = 0) -> DataFrame:
    ids = spark.range(d).withColumnRenamed("id", "coord")
    return ids.orderBy(shuffle_key(F.col("coord"), seed, t), "coord").limit(n)


def recover_random_candidates(d, k, p, vector, seed=0, t=0, reduce="sum", workers=1) -> DataFrame:
    """The limit of an empty sketch: best k of p * k coordinates picked at random."""
    asked = random_coords(vector.sparkSession, d, p * k, seed, t)
    return exact_refetch(vector, asked, p * k, reduce, workers).orderBy(*by_size("exact")).limit(k)


def true_top_k(vector: DataFrame, k: int) -> DataFrame:
    """(coord, value): exact k largest of the aggregated vector."""
    return vector.groupBy("coord").agg(F.sum("delta").alias("value")).orderBy(*by_size("value")).limit(k)


def random_k(vector: DataFrame, k: int, seed: int = 0, t: int = 0) -> DataFrame:
    total = vector.groupBy("coord").agg(F.sum("delta").alias("value"))
    return total.orderBy(shuffle_key(F.col("coord"), seed, t), "coord").limit(k)


def local_top_k(vector: DataFrame, k: int, salts: int = 16) -> DataFrame:
    """(worker, coord, value): each worker's own k largest.

    Two levels: the best k of each part of a worker's coordinates, then of those salts * k.
    """
    own = vector.groupBy("worker", "coord").agg(F.sum("delta").alias("value")).withColumn("_s", F.col("coord") % salts)
    for keys in (("worker", "_s"), ("worker",)):
        w = Window.partitionBy(*keys).orderBy(*by_size("value"))
        own = own.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= k).drop("_n")
    return own.drop("_s")


def split_groups(g: DataFrame, groups: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(compressed, dense) parts of g by coordinate ranges groups(lo, hi, name, compressed)."""
    named = g.join(F.broadcast(groups), (g["coord"] >= groups["lo"]) & (g["coord"] < groups["hi"]), "left")
    packed = F.coalesce("compressed", F.lit(True))
    return named.where(packed).select(*g.columns), named.where(~packed).select(*g.columns)


def contraction_ratio(vector: DataFrame, kept: DataFrame) -> DataFrame:
    """One row: squared norm of what an operator drops, over the squared norm."""
    total = vector.groupBy("coord").agg(F.sum("delta").cast("double").alias("x"))
    left = total.join(kept.select("coord").withColumn("_in", F.lit(1)), "coord", "left")
    sq = F.col("x") * F.col("x")
    return left.agg((F.sum(F.when(F.col("_in").isNull(), sq).otherwise(0.0)) / F.sum(sq)).alias("ratio"))
