"""The relational operators around the methods: scans, joins, windows, sets, arrays, text."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from gradsift.operators import recover as R
from gradsift.operators import sketch as S
from gradsift.sources.tables import SCHEMAS, load_table
from gradsift.workloads import fixtures as X
from gradsift.workloads.cost_queries import GRID_SQL, grid, union_cap
from gradsift.workloads.fixtures import FAM
from gradsift.workloads.registry import query
from gradsift.workloads.sketch_queries import C2, E2, HEAVY, norm_sql, total_sql


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in SCHEMAS))
def scan_counts(spark, d):
    return reduce(lambda a, b: a.unionByName(b), [load_table(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n") for t in SCHEMAS])


# text features: odd weights, reduced by the prime field before the bucket


TRIGRAM_SQL = """SELECT doc_id, CAST((unicode(substr(t, i, 1)) * 961 + unicode(substr(t, i + 1, 1)) * 31 + unicode(substr(t, i + 2, 1))) * 7919 % 2147483647 % 16384 AS BIGINT) AS coord
 FROM (SELECT doc_id, t, unnest(range(1, length(t) - 1)) AS i FROM (SELECT doc_id, lower(text) AS t FROM documents))"""


def document_trigrams(spark, d, buckets: int = 16384):
    """doc_id, coord and n as arrays: hashed character trigrams of the whole lower-cased text, counted inside their row (doc_id is unique); texts below three characters have none."""

    def run(batches):
        for b in batches:
            coords, counts = [], []
            for t in b.column("t").to_pylist():
                p = np.frombuffer((t or "").encode("utf-32-le"), "<u4").astype(np.int64)
                c, n = np.unique((p[:-2] * 961 + p[1:-1] * 31 + p[2:]) * 7919 % 2147483647 % 16384 % buckets, return_counts=True)
                coords.append(c), counts.append(n)
            many = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(coords, many), pa.array(counts, many)], ["doc_id", "coord", "n"])

    docs = load_table(spark, d, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("t"))
    return docs.mapInArrow(run, "doc_id long, coord array<long>, n array<long>")


@query("char_trigrams", f"SELECT doc_id, coord, count(*) AS n FROM ({TRIGRAM_SQL}) GROUP BY doc_id, coord")
def char_trigrams(spark, d):
    return document_trigrams(spark, d).select("doc_id", F.inline(F.arrays_zip("coord", "n")))


@query("ngram_counts", f"SELECT coord, count(*) AS n FROM ({TRIGRAM_SQL}) GROUP BY coord")
def ngram_counts(spark, d):
    return char_trigrams(spark, d).groupBy("coord").agg(F.sum("n").alias("n"))


@query("signed_delta_by_part", f"SELECT coord, CAST(sum(delta) AS BIGINT) AS total, CAST(sum(CASE WHEN delta < 0 THEN delta ELSE 0 END) AS BIGINT) AS returned FROM ({X.f1()}) GROUP BY coord")
def signed_delta_by_part(spark, d):
    return X.signed_part_revenue(spark, d).groupBy("coord").agg(F.sum("delta").alias("total"), F.sum(F.when(F.col("delta") < 0, F.col("delta")).otherwise(0)).alias("returned"))


@query(
    "standardised_features",
    """SELECT p_partkey, round((p_size - m) / s, 6) AS size_z, round((p_retailprice - pm) / ps, 6) AS price_z, CAST(substr(p_brand, 7) AS INTEGER) AS brand
    FROM part CROSS JOIN (SELECT avg(p_size) AS m, stddev_pop(p_size) AS s, avg(p_retailprice) AS pm, stddev_pop(p_retailprice) AS ps FROM part)""",
)
def standardised_features(spark, d):
    p = load_table(spark, d, "part")
    m = p.agg(F.avg("p_size").alias("m"), F.stddev_pop("p_size").alias("s"), F.avg("p_retailprice").alias("pm"), F.stddev_pop("p_retailprice").alias("ps"))
    z = lambda c, a, b: F.round((F.col(c) - F.col(a)) / F.col(b), 6)
    return p.crossJoin(F.broadcast(m)).select("p_partkey", z("p_size", "m", "s").alias("size_z"), z("p_retailprice", "pm", "ps").alias("price_z"), F.substring("p_brand", 7, 9).cast("int").alias("brand"))


def minibatch(df, key: str, t: int, share: int, seed: int):
    """Rows of step t: a seeded hash of the key falls below share of 1000."""
    return df.where(R.shuffle_key(F.col(key), seed, t) % 1000 < share)


@query("minibatch_rows", f"SELECT o_orderkey FROM orders WHERE {R.sql_shuffle_key('o_orderkey', 5, 3)} % 1000 < 100")
def minibatch_rows(spark, d):
    return minibatch(load_table(spark, d, "orders"), "o_orderkey", 3, 100, 5).select("o_orderkey")


@query("split_sizes", f"SELECT CASE WHEN {R.sql_shuffle_key('doc_id', 1)} % 10 < 2 THEN 'test' ELSE 'train' END AS part, count(*) AS n FROM documents GROUP BY 1")
def split_sizes(spark, d):
    part = F.when(R.shuffle_key(F.col("doc_id"), 1) % 10 < 2, "test").otherwise("train")
    return load_table(spark, d, "documents").groupBy(part.alias("part")).agg(F.count("*").alias("n"))


WEIGHTED = f"SELECT l_orderkey AS ex, CAST(sum(CAST(l_quantity AS BIGINT) * (l_partkey * 37 % 11 - 5)) AS BIGINT) AS score FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_orderkey"


def _weighted(spark, d, hint: str):
    w = load_table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), (F.col("p_partkey") * 37 % 11 - 5).alias("w"))
    lines = load_table(spark, d, "lineitem").select("l_orderkey", "l_partkey", F.col("l_quantity").cast("long").alias("q"))
    joined = lines.join(w.hint(hint), "l_partkey")
    return joined.groupBy(F.col("l_orderkey").alias("ex")).agg(F.sum(F.col("q") * F.col("w")).alias("score"))


@query("join_broadcast_weights", WEIGHTED)
def join_broadcast_weights(spark, d):
    """Dot products with a weight table small enough to broadcast (checked by its count)."""
    return _weighted(spark, d, "broadcast" if X.parts(spark, d) <= 2_000_000 else "merge")


@query("join_merge_weights", WEIGHTED)
def join_merge_weights(spark, d):
    """The same for a weight table of any size."""
    return _weighted(spark, d, "merge")


STATE = f"SELECT worker, coord, CAST(sum(delta) AS BIGINT) AS delta FROM ({X.f1()}) WHERE coord % 3 {{}} GROUP BY worker, coord"


@query(
    "state_outer_join",
    f"SELECT coalesce(a.worker, b.worker) AS worker, coalesce(a.coord, b.coord) AS coord, coalesce(a.delta, 0) + coalesce(b.delta, 0) AS v FROM ({STATE.format('<> 0')}) a FULL OUTER JOIN ({STATE.format('<> 1')}) b ON a.worker = b.worker AND a.coord = b.coord",
)
def state_outer_join(spark, d):
    """Residual plus gradient, where either may lack a coordinate."""
    v = X.signed_part_revenue(spark, d)
    own = lambda c, n: v.where(c).groupBy("worker", "coord").agg(F.sum("delta").alias(n))
    both = own("coord % 3 <> 0", "a").join(own("coord % 3 <> 1", "b").hint("shuffle_hash"), ["worker", "coord"], "full")
    return both.select("worker", "coord", (F.coalesce("a", F.lit(0)) + F.coalesce("b", F.lit(0))).alias("v"))


@query("heavy_split", f"SELECT e.coord, h.coord IS NOT NULL AS heavy FROM ({E2}) e LEFT JOIN ({HEAVY}) h ON e.coord = h.coord")
def heavy_split(spark, d):
    """Heavy coordinates by semi join, the others by anti join."""
    cells = S.sketch(X.planted_part_revenue(spark, d), FAM)
    est, heavy = S.estimate_all(cells, FAM, X.parts(spark, d)), S.heavy_hitters(cells, FAM, X.parts(spark, d), 1 / 64)
    side = lambda how, flag: est.join(heavy.select("coord"), "coord", how).select("coord", F.lit(flag).alias("heavy"))
    return side("left_semi", True).unionByName(side("left_anti", False))


@query("mask_anti", f"SELECT * FROM ({total_sql(X.f1())}) WHERE coord NOT IN (SELECT coord FROM ({HEAVY}))")
def mask_anti(spark, d):
    total = X.signed_part_revenue(spark, d).groupBy("coord").agg(F.sum("delta").alias("value"))
    heavy = S.heavy_hitters(S.sketch(X.planted_part_revenue(spark, d), FAM), FAM, X.parts(spark, d), 1 / 64)
    return total.join(heavy.select("coord"), "coord", "left_anti")


GROUPS = [(0, 50, "bias", False), (50, 600, "embed", True), (600, 100_000_000, "body", True)]
GROUPS_SQL = "(VALUES " + ", ".join(f"({a}, {b}, '{n}', {str(c).lower()})" for a, b, n, c in GROUPS) + ") AS g(lo, hi, name, compressed)"


def param_groups(spark):
    return spark.createDataFrame(GROUPS, "lo long, hi long, name string, compressed boolean")


@query("group_range_join", f"SELECT name, compressed, count(*) AS n, CAST(sum(value) AS BIGINT) AS value FROM ({total_sql(X.f1())}) JOIN {GROUPS_SQL} ON coord >= lo AND coord < hi GROUP BY name, compressed")
def group_range_join(spark, d):
    total = X.signed_part_revenue(spark, d).groupBy("coord").agg(F.sum("delta").alias("value"))
    g = F.broadcast(param_groups(spark))
    return total.join(g, (F.col("coord") >= F.col("lo")) & (F.col("coord") < F.col("hi"))).groupBy("name", "compressed").agg(F.count("*").alias("n"), F.sum("value").alias("value"))


@query(
    "bias_exempt_sketch",
    f"""SELECT 'compressed' AS part, row, bucket, CAST(sum(delta * sign) AS BIGINT) AS value FROM ({X.FAM.sql_cells(f"(SELECT coord, delta FROM ({X.f1()}) WHERE coord >= 50)", keep="delta")}) GROUP BY row, bucket
    UNION ALL SELECT 'dense', -1, CAST(coord AS INTEGER), CAST(sum(delta) AS BIGINT) FROM ({X.f1()}) WHERE coord < 50 GROUP BY coord""",
)
def bias_exempt_sketch(spark, d):
    """What is sent when the first coordinates go uncompressed: the cells of the others, and their own sums (row -1)."""
    packed, dense = R.split_groups(X.signed_part_revenue(spark, d), param_groups(spark))
    cells = S.sketch(packed, X.FAM).select(F.lit("compressed").alias("part"), "row", "bucket", F.col("cell").alias("value"))
    own = dense.groupBy("coord").agg(F.sum("delta").alias("value"))
    return cells.unionByName(own.select(F.lit("dense").alias("part"), F.lit(-1).alias("row"), F.col("coord").cast("int").alias("bucket"), "value"))


KINDS = ["click", "error", "purchase", "signup", "view"]


@query(
    "one_hot_events",
    "SELECT user_id, " + ", ".join(f"CAST(sum(CASE WHEN event_type = '{k}' THEN 1 ELSE 0 END) AS BIGINT) AS {k}" for k in KINDS) + ", CAST(sum(CASE WHEN event_type IN (" + ", ".join(f"'{k}'" for k in KINDS) + ") THEN 0 ELSE 1 END) AS BIGINT) AS other FROM events GROUP BY user_id",
)
def one_hot_events(spark, d):
    """Event kinds as one-hot vectors (the last place is for any other kind), added up by user."""
    place = F.coalesce(F.nullif(F.array_position(F.array(*map(F.lit, KINDS)), F.col("event_type")), F.lit(0)), F.lit(len(KINDS) + 1))
    hot = F.transform(F.sequence(F.lit(1), F.lit(len(KINDS) + 1)), lambda i: (i == place).cast("long"))
    rows = load_table(spark, d, "events").select("user_id", hot.alias("x"))
    return rows.groupBy("user_id").agg(*(F.sum(F.get("x", F.lit(i))).alias(k) for i, k in enumerate([*KINDS, "other"])))


@query(
    "approx_distinct_parts",
    "SELECT CAST(l_orderkey % 4 AS INTEGER) AS worker, count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem GROUP BY 1",
)
def approx_distinct_parts(spark, d):
    """Coordinates that each worker touches: counted, and estimated within five per cent by the built-in sketch."""
    rows = X.signed_part_revenue(spark, d).groupBy("worker").agg(F.countDistinct("coord").alias("exact"), F.approx_count_distinct("coord", 0.01).alias("estimate"))
    return rows.select("worker", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.05 * F.col("exact")).alias("near"))


@query(
    "events_interval_join",
    """SELECT e.event_id AS error_id, n.event_id AS next_id FROM events e JOIN events n ON e.user_id = n.user_id
    AND n.ts > e.ts AND n.ts <= e.ts + INTERVAL 30 MINUTE WHERE e.event_type = 'error' AND n.event_type <> 'error'""",
)
def events_interval_join(spark, d):
    """Events within half an hour of an error by the same user: equal time bins first, then the exact condition."""
    ev = load_table(spark, d, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 1800).alias("bin"))
    err = ev.where("event_type = 'error'").select("user_id", F.col("event_id").alias("error_id"), F.col("ts").alias("t0"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    near = ev.where("event_type <> 'error'").join(err, ["user_id", "bin"])
    return near.where((F.col("ts") > F.col("t0")) & (F.col("ts") <= F.col("t0") + F.expr("interval 30 minutes"))).select("error_id", F.col("event_id").alias("next_id"))


@query(
    "asof_version",
    """SELECT e.event_id, max(v.event_id) AS version FROM events e LEFT JOIN (SELECT event_id, user_id FROM events WHERE event_type = 'purchase') v
    ON e.user_id = v.user_id AND v.event_id <= e.event_id GROUP BY e.event_id""",
)
def asof_version(spark, d):
    """Last purchase of the user at or before each event, by one window over ids in time order."""
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    version = F.max(F.when(F.col("event_type") == "purchase", F.col("event_id"))).over(w)
    return load_table(spark, d, "events").select("event_id", version.alias("version"))


COSTS_SQL = "(SELECT m AS method, w AS W, p AS P, CASE WHEN m = 'sketch' THEN 5550 + p * 200 + 200 ELSE 200 + least(200 * w, 65536) END AS numbers FROM (VALUES ('sketch'), ('local_top_k')) AS a(m) CROSS JOIN (VALUES (1), (16), (256)) AS b(w) CROSS JOIN (VALUES (4), (16)) AS c(p))"


def costs(spark):
    from gradsift.plans import cost as C

    rows = [(m, w, p, int(C.comm_sketch(5, 1110, p, 200)) if m == "sketch" else C.comm_local(200, C.local_union_cap(200, w, 65_536))) for m in ("sketch", "local_top_k") for w in (1, 16, 256) for p in (4, 16)]
    return spark.createDataFrame(rows, "method string, W int, P int, numbers int")


MONTHLY_SQL = "(SELECT model, m AS method, w AS W, p AS P, CASE WHEN m = 'sketch' THEN r * c + p * k + k ELSE k + least(k * w, d) END AS numbers FROM (SELECT model, d, r, c, k FROM " + GRID_SQL + " WHERE g.method = 'language_20x') CROSS JOIN (VALUES ('sketch'), ('local_top_k')) AS a(m) CROSS JOIN (VALUES (1), (16), (256)) AS b(w) CROSS JOIN (VALUES (4), (16)) AS e(p))"


def monthly_costs(spark, d):
    """model, method, W, P, numbers: what a step over the vector of each month of orders costs."""
    from gradsift.plans import cost as C

    n, r, c, k, w, p = (F.col(x) for x in ("d", "r", "c", "k", "W", "P"))
    rows = grid(spark, d).where("method = 'language_20x'").select("model", "d", "r", "c", "k")
    for name, values in (("method", ("sketch", "local_top_k")), ("W", (1, 16, 256)), ("P", (4, 16))):
        rows = rows.withColumn(name, F.explode(F.array(*map(F.lit, values))))
    numbers = F.when(F.col("method") == "sketch", C.comm_sketch(r, c, p, k).cast("long")).otherwise(C.comm_local(k, union_cap(k, w, n)))
    return rows.select("model", "method", "W", "P", numbers.alias("numbers"))


@query("cost_rollup", f"SELECT method, W, P, CAST(sum(numbers) AS BIGINT) AS numbers FROM {MONTHLY_SQL} GROUP BY ROLLUP (method, W, P)")
def cost_rollup(spark, d):
    return monthly_costs(spark, d).rollup("method", "W", "P").agg(F.sum("numbers").alias("numbers"))


@query("cost_cube", f"SELECT method, W, CAST(sum(numbers) AS BIGINT) AS numbers FROM {MONTHLY_SQL} GROUP BY CUBE (method, W)")
def cost_cube(spark, d):
    return monthly_costs(spark, d).cube("method", "W").agg(F.sum("numbers").alias("numbers"))


@query("cost_grouping_sets", f"SELECT method, W, CAST(sum(numbers) AS BIGINT) AS numbers FROM {MONTHLY_SQL} GROUP BY GROUPING SETS ((method), (W), ())")
def cost_grouping_sets(spark, d):
    monthly_costs(spark, d).createOrReplaceTempView("costs")
    return spark.sql("SELECT method, W, sum(numbers) AS numbers FROM costs GROUP BY GROUPING SETS ((method), (W), ())")


@query("summary_pivot", f"SELECT method, max(CASE WHEN W = 1 THEN numbers END) AS w1, max(CASE WHEN W = 16 THEN numbers END) AS w16, max(CASE WHEN W = 256 THEN numbers END) AS w256 FROM {COSTS_SQL} WHERE P = 4 GROUP BY method")
def summary_pivot(spark, d):
    p = costs(spark).where("P = 4").groupBy("method").pivot("W", [1, 16, 256]).agg(F.max("numbers"))
    return p.toDF("method", "w1", "w16", "w256")


@query("rank_ties", "SELECT c_custkey, rank() OVER w AS rnk, dense_rank() OVER w AS dense, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey, c_custkey) AS quarter FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)")
def rank_ties(spark, d):
    w = Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    q = Window.partitionBy("c_mktsegment").orderBy("c_nationkey", "c_custkey")
    return load_table(spark, d, "customer").select("c_custkey", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(q).alias("quarter"))


DAILY = "(SELECT user_id, CAST(date_trunc('day', ts) AS DATE) AS day, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS v FROM events GROUP BY 1, 2)"


def daily(spark, d):
    return load_table(spark, d, "events").groupBy("user_id", F.to_date("ts").alias("day")).agg(F.sum(X.cents("value")).alias("v"))


@query("loss_delta", f"SELECT user_id, day, v - lag(v) OVER w AS change, lead(v) OVER w AS following, first_value(v) OVER w AS opening FROM {DAILY} WINDOW w AS (PARTITION BY user_id ORDER BY day)")
def loss_delta(spark, d):
    w = Window.partitionBy("user_id").orderBy("day")
    return daily(spark, d).select("user_id", "day", (F.col("v") - F.lag("v").over(w)).alias("change"), F.lead("v").over(w).alias("following"), F.first("v").over(w).alias("opening"))


@query("smoothed_curve", f"SELECT user_id, day, round(avg(v) OVER (PARTITION BY user_id ORDER BY day ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 6) AS smooth FROM {DAILY}")
def smoothed_curve(spark, d):
    w = Window.partitionBy("user_id").orderBy("day").rowsBetween(-9, 0)
    return daily(spark, d).select("user_id", "day", F.round(F.avg("v").over(w), 6).alias("smooth"))


@query("running_mass", f"SELECT user_id, day, CAST(sum(v) OVER (PARTITION BY user_id ORDER BY date_diff('day', DATE '2024-01-01', day) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM {DAILY}")
def running_mass(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.datediff("day", F.lit("2024-01-01"))).rangeBetween(-6, 0)
    return daily(spark, d).select("user_id", "day", F.sum("v").over(w).alias("week"))


@query(
    "mass_curve",
    f"SELECT coord, round(sum(v * v) OVER (ORDER BY abs(v) DESC, coord) / sum(v * v) OVER (), 6) AS share FROM (SELECT coord, CAST(value AS DOUBLE) AS v FROM ({total_sql(X.f2())}) ORDER BY abs(value) DESC, coord LIMIT 200)",
)
def mass_curve(spark, d):
    """Cumulative share of the squared mass among the 200 largest coordinates (a top-k report)."""
    top = X.planted_part_revenue(spark, d).groupBy("coord").agg(F.sum("delta").cast("double").alias("v")).orderBy(*S.by_size("v")).limit(200)
    sq = F.col("v") * F.col("v")
    return top.select("coord", F.round(F.sum(sq).over(Window.orderBy(*S.by_size("v"))) / F.sum(sq).over(Window.partitionBy(F.lit(1))), 6).alias("share"))


@query("decayed_spend", "SELECT user_id, round(sum(value * exp(-date_diff('day', CAST(ts AS DATE), DATE '2024-02-01') / 10.0::DOUBLE)), 4) AS spend FROM events GROUP BY user_id")
def decayed_spend(spark, d):
    age = F.datediff(F.lit("2024-02-01"), F.to_date("ts"))
    return load_table(spark, d, "events").groupBy("user_id").agg(F.round(F.sum(F.col("value") * F.exp(-age / 10.0)), 4).alias("spend"))


@query("embedding_dot", "SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda i: CAST(embedding[i] AS DOUBLE) * (((i - 1) * 37 % 11) - 5))), 4) AS dot FROM embeddings")
def embedding_dot(spark, d):
    w = F.array(*(F.lit(float(i * 37 % 11 - 5)) for i in range(64)))
    dot = F.aggregate(F.zip_with(F.col("embedding").cast("array<double>"), w, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    return load_table(spark, d, "embeddings").select("vec_id", F.round(dot, 4).alias("dot"))


@query("array_median", "SELECT vec_id, round((s[32] + s[33]) / 2, 6) AS med FROM (SELECT vec_id, list_sort(list_transform(embedding, lambda x: CAST(x AS DOUBLE))) AS s FROM embeddings)")
def array_median(spark, d):
    s = F.array_sort(F.col("embedding").cast("array<double>"))
    return load_table(spark, d, "embeddings").select("vec_id", F.round((F.element_at(s, 32) + F.element_at(s, 33)) / 2, 6).alias("med"))


@query("norm_of_merged", norm_sql(C2))
def norm_of_merged(spark, d):
    return S.norm2(S.merge(S.sketch(X.planted_part_revenue(spark, d), FAM, by=["worker"])))


@query(
    "map_vector_add",
    f"SELECT g, coord, CAST(sum(delta) AS BIGINT) AS total FROM (SELECT coord % 10 AS g, coord, delta FROM ({X.f1(2)}) WHERE coord < 500) GROUP BY g, coord",
)
def map_vector_add(spark, d):
    """Two sparse vectors as maps, added key by key."""
    v = X.signed_part_revenue(spark, d, 2).where("coord < 500").groupBy("worker", "coord").agg(F.sum("delta").alias("s"))
    maps = v.groupBy((F.col("coord") % 10).alias("g")).agg(*(F.map_from_entries(F.collect_list(F.when(F.col("worker") == w, F.struct("coord", "s")))).alias(f"m{w}") for w in (0, 1)))
    total = F.map_zip_with("m0", "m1", lambda k, a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)))
    return maps.select("g", F.explode(total).alias("coord", "total"))
