"""Queries on building, merging and querying sketches, and on recovery."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from gradsift.operators import recover as R
from gradsift.operators import sketch as S
from gradsift.sources.tables import load_table
from gradsift.workloads import fixtures as X
from gradsift.workloads.fixtures import FAM
from gradsift.workloads.registry import query


def cells_sql(source: str, by: str = "", keep: str = "coord, delta", group: str = "") -> str:
    """Cells of a source, as a SELECT; by: leading group columns with a comma."""
    return f"SELECT {by}row, bucket, CAST(sum(delta * sign) AS BIGINT) AS cell FROM ({FAM.sql_cells(f'({source})', keep=by + keep)}) GROUP BY {by}row, bucket"


C1, C2, C3 = cells_sql(X.f1()), cells_sql(X.f2()), cells_sql(X.f3())
PARTS = "SELECT p_partkey AS coord FROM part"


def estimates_sql(cells: str, coords: str = PARTS) -> str:
    return (
        f"SELECT a.coord, median(CAST(a.sign * coalesce(c.cell, 0) AS DOUBLE)) AS est FROM ({FAM.sql_cells(f'({coords})', keep='coord')}) a "
        f"LEFT JOIN ({cells}) c ON a.row = c.row AND a.bucket = c.bucket GROUP BY a.coord"
    )


def row_norms_sql(cells: str) -> str:
    return f"SELECT row, CAST(sum(CAST(cell AS HUGEINT) * CAST(cell AS HUGEINT)) AS DOUBLE) AS norm2 FROM ({cells}) GROUP BY row"


def norm_sql(cells: str) -> str:
    return f"SELECT median(norm2) AS norm2 FROM ({row_norms_sql(cells)})"


def total_sql(source: str) -> str:
    return f"SELECT coord, CAST(sum(delta) AS BIGINT) AS value FROM ({source}) GROUP BY coord"


def exact_norm(vector):
    t = vector.groupBy("coord").agg(F.sum("delta").cast("decimal(19,0)").alias("x"))
    return t.agg(F.sum(F.col("x") * F.col("x")).cast("double").alias("exact"))


def exact_norm_sql(source: str) -> str:
    return f"SELECT CAST(sum(CAST(value AS HUGEINT) * CAST(value AS HUGEINT)) AS DOUBLE) AS exact FROM ({total_sql(source)})"


@query("sketch_cells", C1)
def sketch_cells(spark, d):
    return S.sketch(X.signed_part_revenue(spark, d), FAM)


@query("sketch_cells_numpy_kernel", C1)
def sketch_cells_numpy_kernel(spark, d):
    return S.sketch_blocks(X.signed_part_revenue(spark, d), FAM)


BY_WORKER = cells_sql(X.f1(), "worker, ")


@query("sketch_cells_by_worker", BY_WORKER)
def sketch_cells_by_worker(spark, d):
    return S.sketch(X.signed_part_revenue(spark, d), FAM, by=["worker"])


@query("sketch_merge_sum", C1)
def sketch_merge_sum(spark, d):
    return S.merge(sketch_cells_by_worker(spark, d))


@query("sketch_merge_mean", f"SELECT row, bucket, cell / 4.0::DOUBLE AS cell FROM ({C1})")
def sketch_merge_mean(spark, d):
    return S.merge(sketch_cells_by_worker(spark, d), "mean", workers=4)


SIGNED = "SELECT l_partkey AS coord, CAST(round(l_extendedprice * 100) AS BIGINT) * {} AS delta FROM lineitem WHERE l_returnflag {} 'R'"


@query("sketch_subtract", cells_sql(f"{SIGNED.format(1, '<>')} UNION ALL {SIGNED.format(-1, '=')}"))
def sketch_subtract(spark, d):
    lines = load_table(spark, d, "lineitem")
    of = lambda cond: S.sketch(lines.where(cond).select(F.col("l_partkey").alias("coord"), X.cents("l_extendedprice").alias("delta")), FAM)
    return S.subtract(of("l_returnflag <> 'R'"), of("l_returnflag = 'R'"))


@query("sketch_scale", f"SELECT row, bucket, CAST(cell * 3 AS BIGINT) AS cell FROM ({C1})")
def sketch_scale(spark, d):
    return S.scale(sketch_cells(spark, d), 3)


ROLLUP_SOURCE = f"""SELECT r_name AS region, coord, delta FROM ({X.f3()}) u JOIN customer ON coord = c_custkey
 JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""


@query("sketch_rollup", cells_sql(ROLLUP_SOURCE, "region, "))
def sketch_rollup(spark, d):
    """Cells per region from cells per nation: the sketch of a roll-up is the sum of its children."""
    spend = X.customer_spend(spark, d).join(load_table(spark, d, "customer").select(F.col("c_custkey").alias("coord"), "c_nationkey"), "coord")
    nations = S.sketch(spend, FAM, by=["c_nationkey"])
    up = load_table(spark, d, "nation").join(load_table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    up = up.select(F.col("n_nationkey").alias("c_nationkey"), F.col("r_name").alias("region"))
    return S.merge(nations.join(up, "c_nationkey"), by=["region"])


@query(
    "point_query",
    f"SELECT e.coord, e.est, coalesce(t.value, 0) AS exact FROM ({estimates_sql(C2, PARTS + ' WHERE p_partkey % 97 = 0')}) e LEFT JOIN ({total_sql(X.f2())}) t ON e.coord = t.coord",
)
def point_query(spark, d):
    v = X.planted_part_revenue(spark, d)
    coords = spark.range(0, X.parts(spark, d), 97).withColumnRenamed("id", "coord")
    exact = v.where("coord % 97 = 0").groupBy("coord").agg(F.sum("delta").alias("exact"))
    return S.estimate(S.sketch(v, FAM), FAM, coords).join(exact, "coord", "left").withColumn("exact", F.coalesce("exact", F.lit(0)))


E2 = estimates_sql(C2)


@query("estimate_all", E2)
def estimate_all(spark, d):
    return S.estimate_all(S.sketch(X.planted_part_revenue(spark, d), FAM), FAM, X.parts(spark, d))


@query("estimate_all_numpy_kernel", E2)
def estimate_all_numpy_kernel(spark, d):
    return S.estimate_all(S.sketch(X.planted_part_revenue(spark, d), FAM), FAM, X.parts(spark, d), kernel="numpy")


VECTORS = {"signed": (X.signed_part_revenue, X.f1()), "planted": (X.planted_part_revenue, X.f2()), "spend": (X.customer_spend, X.f3())}


@query(
    "norm2_estimate",
    " UNION ALL ".join(
        f"SELECT '{n}' AS fixture, norm2 AS est, exact, round(norm2 / exact, 6) AS ratio FROM ({norm_sql(cells_sql(q))}) CROSS JOIN ({exact_norm_sql(q)})" for n, (_, q) in VECTORS.items()
    ),
)
def norm2_estimate(spark, d):
    out = []
    for name, (make, _) in VECTORS.items():
        v = make(spark, d)
        both = S.norm2(S.sketch(v, FAM)).crossJoin(F.broadcast(exact_norm(v)))
        out.append(both.select(F.lit(name).alias("fixture"), F.col("norm2").alias("est"), "exact", F.round(F.col("norm2") / F.col("exact"), 6).alias("ratio")))
    return reduce(lambda a, b: a.unionByName(b), out)


@query(
    "norm_error_rows",
    " UNION ALL ".join(
        f"SELECT '{n}' AS fixture, row, norm2 AS est, exact, round(norm2 / exact, 6) AS ratio FROM ({row_norms_sql(cells_sql(q))}) CROSS JOIN ({exact_norm_sql(q)})" for n, (_, q) in VECTORS.items()
    ),
)
def norm_error_rows(spark, d):
    out = []
    for name, (make, _) in VECTORS.items():
        v = make(spark, d)
        both = S.row_norms(S.sketch(v, FAM)).crossJoin(F.broadcast(exact_norm(v)))
        out.append(both.select(F.lit(name).alias("fixture"), "row", F.col("norm2").alias("est"), "exact", F.round(F.col("norm2") / F.col("exact"), 6).alias("ratio")))
    return reduce(lambda a, b: a.unionByName(b), out)


HEAVY = f"SELECT coord, est FROM ({E2}) CROSS JOIN ({norm_sql(C2)}) WHERE est * est > norm2 / 64"


@query("heavy_hitters", HEAVY)
def heavy_hitters(spark, d):
    return S.heavy_hitters(S.sketch(X.planted_part_revenue(spark, d), FAM), FAM, X.parts(spark, d), 1 / 64)


def top_sql(frame: str, value: str, k: int) -> str:
    return f"SELECT * FROM (SELECT *, row_number() OVER (ORDER BY abs({value}) DESC, coord) AS rnk FROM ({frame})) WHERE rnk <= {k}"


def ranked(df, value):
    from pyspark.sql import Window

    return df.withColumn("rnk", F.row_number().over(Window.orderBy(*S.by_size(value))))  # k rows


@query("approx_top_k", f"SELECT coord, est, CAST(rnk AS INTEGER) AS rnk FROM ({top_sql(E2, 'est', 20)})")
def approx_top_k(spark, d):
    return ranked(S.approx_top_k(S.sketch(X.planted_part_revenue(spark, d), FAM), FAM, X.parts(spark, d), 20), "est")


HEAVY_OR_RANDOM = f"""
WITH e AS (SELECT coord, est, est * est >= norm2 / 16 AS is_heavy, {R.sql_shuffle_key('coord', 7)} AS key FROM ({E2}) CROSS JOIN ({norm_sql(C2)}) WHERE norm2 > 0),
p AS (SELECT coord, is_heavy FROM (SELECT *, row_number() OVER (ORDER BY is_heavy DESC, CASE WHEN is_heavy THEN abs(est) END DESC NULLS LAST, key, coord) AS n FROM e) WHERE n <= 16)
SELECT p.coord, p.is_heavy, coalesce(t.value, 0) AS exact FROM p LEFT JOIN ({total_sql(X.f2())}) t ON p.coord = t.coord
"""


@query("recover_heavy_or_random", HEAVY_OR_RANDOM)
def recover_heavy_or_random(spark, d):
    v = X.planted_part_revenue(spark, d)
    return R.recover_heavy_or_random(S.sketch(v, FAM), FAM, X.parts(spark, d), 16, v, seed=7)


def refetch_sql(picks: str, source: str) -> str:
    return f"SELECT p.coord, coalesce(t.value, 0) AS exact FROM ({picks}) p LEFT JOIN ({total_sql(source)}) t ON p.coord = t.coord"


@query("recover_over_ask", f"SELECT coord, exact, CAST(rnk AS INTEGER) AS rnk FROM ({top_sql(refetch_sql(top_sql(E2, 'est', 64), X.f2()), 'exact', 16)})")
def recover_over_ask(spark, d):
    v = X.planted_part_revenue(spark, d)
    return ranked(R.recover_over_ask(S.sketch(v, FAM), FAM, X.parts(spark, d), 16, 4, v), "exact")


@query("recover_without_refetch", f"SELECT coord, est AS exact FROM ({top_sql(E2, 'est', 16)})")
def recover_without_refetch(spark, d):
    v = X.planted_part_revenue(spark, d)
    return R.recover_over_ask(S.sketch(v, FAM), FAM, X.parts(spark, d), 16, 4, v, refetch=False)


def random_sql(k: int, seed: int, frame: str = PARTS) -> str:
    return f"SELECT * FROM ({frame}) ORDER BY {R.sql_shuffle_key('coord', seed)}, coord LIMIT {k}"


@query("recover_random_candidates", f"SELECT coord, exact FROM ({top_sql(refetch_sql(random_sql(64, 3), X.f2()), 'exact', 16)})")
def recover_random_candidates(spark, d):
    return R.recover_random_candidates(X.parts(spark, d), 16, 4, X.planted_part_revenue(spark, d), seed=3)


IDS = [0, 3, 97, 101, 194]


@query("exact_refetch", f"SELECT coord, worker, CAST(sum(delta) AS BIGINT) AS exact FROM ({X.f1()}) WHERE coord IN (0, 3, 97, 101, 194) GROUP BY GROUPING SETS ((coord, worker), (coord))")
def exact_refetch(spark, d):
    """Exact values of a fixed id list, per worker and in total (null worker)."""
    ids = spark.createDataFrame([(i,) for i in IDS], "coord long")
    own = X.signed_part_revenue(spark, d).join(F.broadcast(ids), "coord", "left_semi").groupBy("coord", "worker").agg(F.sum("delta").alias("exact"))
    return own.unionByName(own.groupBy("coord").agg(F.sum("exact").alias("exact")).withColumn("worker", F.lit(None).cast("int")))


T1 = total_sql(X.f1())


@query("true_top_k", f"SELECT coord, value FROM ({top_sql(T1, 'value', 50)})")
def true_top_k(spark, d):
    return R.true_top_k(X.signed_part_revenue(spark, d), 50)


@query("random_k", random_sql(50, 11, T1))
def random_k(spark, d):
    return R.random_k(X.signed_part_revenue(spark, d), 50, seed=11)


def local_sql(w: int, k: int) -> str:
    own = f"SELECT worker, coord, CAST(sum(delta) AS BIGINT) AS value FROM ({X.f1(w)}) GROUP BY worker, coord"
    return f"SELECT {w} AS W, worker, coord, value FROM (SELECT *, row_number() OVER (PARTITION BY worker ORDER BY abs(value) DESC, coord) AS n FROM ({own})) WHERE n <= {k}"


LOCAL = " UNION ALL ".join(local_sql(w, 50) for w in (1, 4, 16))


@query("local_top_k", LOCAL)
def local_top_k(spark, d):
    parts = [R.local_top_k(X.signed_part_revenue(spark, d, w), 50).withColumn("W", F.lit(w)) for w in (1, 4, 16)]
    return reduce(lambda a, b: a.unionByName(b), parts)


@query("local_union_size", f"SELECT W, count(DISTINCT coord) AS union_size, least(50 * W, (SELECT count(*) FROM part)) AS cap FROM ({LOCAL}) GROUP BY W")
def local_union_size(spark, d):
    """Coordinates updated by local top-k against min(k * W, d)."""
    n = X.parts(spark, d)
    return local_top_k(spark, d).groupBy("W").agg(F.countDistinct("coord").alias("union_size")).withColumn("cap", F.least(F.col("W") * 50, F.lit(n)).cast("long"))


@query("union_workers", f"SELECT DISTINCT coord FROM ({local_sql(4, 50)})")
def union_workers(spark, d):
    """Set union of the workers' picks."""
    picks = R.local_top_k(X.signed_part_revenue(spark, d, 4), 50)
    return reduce(lambda a, b: a.union(b), [picks.where(F.col("worker") == w).select("coord") for w in range(4)]).distinct()


TOP2, TRUE2 = top_sql(E2, "est", 20), top_sql(total_sql(X.f2()), "value", 20)


@query("topk_overlap", f"SELECT coord FROM ({TOP2}) INTERSECT SELECT coord FROM ({TRUE2})")
def topk_overlap(spark, d):
    v = X.planted_part_revenue(spark, d)
    return S.approx_top_k(S.sketch(v, FAM), FAM, X.parts(spark, d), 20).select("coord").intersect(R.true_top_k(v, 20).select("coord"))


@query("topk_missed", f"SELECT coord FROM ({TRUE2}) EXCEPT SELECT coord FROM ({TOP2})")
def topk_missed(spark, d):
    v = X.planted_part_revenue(spark, d)
    return R.true_top_k(v, 20).select("coord").exceptAll(S.approx_top_k(S.sketch(v, FAM), FAM, X.parts(spark, d), 20).select("coord"))


RECALL = " UNION ALL ".join(
    f"SELECT {k} AS k, count(*) AS overlap, round(count(*) / {k}.0::DOUBLE, 6) AS recall FROM ({top_sql(E2, 'est', k)}) a JOIN ({top_sql(total_sql(X.f2()), 'value', k)}) b ON a.coord = b.coord"
    for k in (5, 10, 20)
)


@query("recall_table", RECALL)
def recall_table(spark, d):
    v, out = X.planted_part_revenue(spark, d), []
    for k in (5, 10, 20):
        both = S.approx_top_k(S.sketch(v, FAM), FAM, X.parts(spark, d), k).join(R.true_top_k(v, k), "coord")
        out.append(both.agg(F.count("*").alias("overlap")).select(F.lit(k).alias("k"), "overlap", F.round(F.col("overlap") / F.lit(float(k)), 6).alias("recall")))
    return reduce(lambda a, b: a.unionByName(b), out)


def ratio_sql(op: str, k: int, kept: str, source: str) -> str:
    return (
        f"SELECT '{op}' AS op, {k} AS k, round(sum(CASE WHEN p.coord IS NULL THEN v * v ELSE 0 END) / sum(v * v), 6) AS ratio, round(1 - {k} / CAST((SELECT count(*) FROM part) AS DOUBLE), 6) AS bound "
        f"FROM (SELECT coord, CAST(value AS DOUBLE) AS v FROM ({total_sql(source)})) t LEFT JOIN ({kept}) p ON t.coord = p.coord"
    )


@query(
    "contraction_ratios",
    " UNION ALL ".join(
        [
            ratio_sql("top_k", 50, f"SELECT coord FROM ({top_sql(T1, 'value', 50)})", X.f1()),
            ratio_sql("random_k", 50, f"SELECT coord FROM ({random_sql(50, 11, T1)})", X.f1()),
            ratio_sql("heavy_or_random", 16, f"SELECT coord FROM ({HEAVY_OR_RANDOM})", X.f2()),
        ]
    ),
)
def contraction_ratios(spark, d):
    n = X.parts(spark, d)
    v1, v2 = X.signed_part_revenue(spark, d), X.planted_part_revenue(spark, d)
    runs = [("top_k", 50, v1, R.true_top_k(v1, 50)), ("random_k", 50, v1, R.random_k(v1, 50, seed=11)), ("heavy_or_random", 16, v2, recover_heavy_or_random(spark, d))]
    out = [R.contraction_ratio(v, kept).select(F.lit(op).alias("op"), F.lit(k).alias("k"), F.round("ratio", 6).alias("ratio"), F.lit(round(1 - k / n, 6)).alias("bound")) for op, k, v, kept in runs]
    return reduce(lambda a, b: a.unionByName(b), out)


EPS = [0.001, 0.01, 0.05]


@query(
    "query_error_share",
    " UNION ALL ".join(
        f"SELECT {e}::DOUBLE AS eps, round(avg(CASE WHEN abs(est * est - v * v) <= {e}::DOUBLE * exact THEN 1.0::DOUBLE ELSE 0.0 END), 6) AS share FROM ({E2}) e LEFT JOIN (SELECT coord AS c, CAST(value AS DOUBLE) AS w FROM ({total_sql(X.f2())})) t ON e.coord = t.c CROSS JOIN ({exact_norm_sql(X.f2())}) CROSS JOIN LATERAL (SELECT coalesce(w, 0) AS v)"
        for e in EPS
    ),
)
def query_error_share(spark, d):
    v = X.planted_part_revenue(spark, d)
    exact = v.groupBy("coord").agg(F.sum("delta").cast("double").alias("v"))
    est = S.estimate_all(S.sketch(v, FAM), FAM, X.parts(spark, d)).join(exact, "coord", "left").fillna(0.0, ["v"]).crossJoin(F.broadcast(exact_norm(v)))
    gap = F.abs(F.col("est") * F.col("est") - F.col("v") * F.col("v"))
    one = [F.round(F.avg(F.when(gap <= F.lit(e) * F.col("exact"), 1.0).otherwise(0.0)), 6).alias(f"s{i}") for i, e in enumerate(EPS)]
    return est.agg(*one).select(F.inline(F.array(*(F.struct(F.lit(e).alias("eps"), F.col(f"s{i}").alias("share")) for i, e in enumerate(EPS)))))


@query(
    "events_tumbling_sketch",
    f"SELECT window_start, row, bucket, CAST(sum(delta * sign) AS BIGINT) AS cell FROM ({FAM.sql_cells(f'''(SELECT date_trunc('day', ts) AS window_start, coord, delta FROM ({X.F4}))''', keep='window_start, delta')}) GROUP BY window_start, row, bucket",
)
def events_tumbling_sketch(spark, d):
    """Batch twin of the windowed stream: one sketch per day."""
    ev = X.event_updates(spark, d).withColumn("window_start", F.date_trunc("day", "ts"))
    return S.sketch(ev, FAM, by=["window_start"])


@query("events_props_sketch", cells_sql(f"SELECT k AS coord, delta FROM ({X.F4})"))
def events_props_sketch(spark, d):
    return S.sketch(X.event_updates(spark, d).select(F.col("k").alias("coord"), "delta"), FAM)


@query("sql_point_query", estimates_sql(C2, PARTS + " WHERE p_partkey < 10"))
def sql_point_query(spark, d):
    """Point queries in SQL over the views ``cells`` and ``hashes``."""
    S.sketch(X.planted_part_revenue(spark, d), FAM).createOrReplaceTempView("cells")
    FAM.frame(spark).createOrReplaceTempView("hashes")
    p = FAM.field
    poly = lambda k: f"((({k}3 * x + {k}2) % {p} * x + {k}1) % {p} * x + {k}0) % {p}"
    return spark.sql(f"""
      SELECT x AS coord, median(CAST(sign * coalesce(cell, 0) AS DOUBLE)) AS est
      FROM (SELECT x, row, CAST({poly('b')} % {FAM.cols} AS INT) AS bucket, 1 - 2 * ({poly('s')} % 2) AS sign
            FROM (SELECT id AS x FROM range(10)) CROSS JOIN hashes) a LEFT JOIN cells USING (row, bucket) GROUP BY x""")


@query(
    "merge_records_per_worker",
    f"SELECT W, max(n) AS most, {FAM.rows * FAM.cols} AS cap FROM ("
    + " UNION ALL ".join(f"SELECT {w} AS W, worker, count(*) AS n FROM ({cells_sql(X.f1(w), 'worker, ')}) GROUP BY worker" for w in (1, 4, 16, 64))
    + ") GROUP BY W",
)
def merge_records_per_worker(spark, d):
    """Records that a worker ships to the merge, for several numbers of workers, against rows * cols."""
    out = []
    for w in (1, 4, 16, 64):
        own = S.sketch(X.signed_part_revenue(spark, d, w), FAM, by=["worker"]).groupBy("worker").agg(F.count("*").alias("n"))
        out.append(own.agg(F.max("n").alias("most")).select(F.lit(w).alias("W"), "most", F.lit(FAM.rows * FAM.cols).alias("cap")))
    return reduce(lambda a, b: a.unionByName(b), out)
