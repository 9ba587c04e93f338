"""Queries on cost, bounds and accuracy measures: shapes of the text, scaled to the updates of each month of ``orders``."""

from __future__ import annotations

from pyspark.sql import functions as F

from gradsift.operators.quality import corpus_bleu
from gradsift.plans import bounds as B
from gradsift.plans import cost as C
from gradsift.sources.tables import load_table
from gradsift.workloads.registry import query

# method, d, rows, cols, P, k, W: shapes that the text states, then those of our stand-ins
GRID = [
    ("transformer_20x", 90_000_000, 5, 1_000_000, 36, 100_000, 4),
    ("transformer_40x", 90_000_000, 15, 180_000, 16, 100_000, 4),
    ("lstm_40x", 73_000_000, 5, 180_000, 26, 100_000, 4),
    ("char_model_20x", 1_048_576, 5, 13_571, 36, 1_000, 4),
    ("char_model_20x_small_p", 1_048_576, 5, 17_571, 16, 1_000, 4),
    ("char_model_40x", 1_048_576, 15, 2_361, 16, 1_000, 4),
    ("char_model_40x_small_sketch", 1_048_576, 5, 5_085, 26, 1_000, 4),
    ("teacher_17x", 19_210, 5, 302, 4, 150, 4),
    ("teacher_17x_large_k", 19_210, 5, 152, 4, 300, 4),
    ("language_20x", 65_536, 5, 1_110, 4, 200, 256),
    ("language_40x", 65_536, 5, 455, 4, 200, 256),
]
#: Of each shape what does not depend on its size: method, whether the text states it, rows, coordinates for each column and for each value sent, P.
SHAPES = [(m, d > 70_000_000, r, d // c, d // k, p) for m, d, r, c, p, k, _ in GRID]
MODELS_SQL = "(SELECT CAST(year(o_orderdate) * 100 + month(o_orderdate) AS INTEGER) AS model, CAST(count(DISTINCT o_custkey) AS BIGINT) AS d, CAST(count(DISTINCT CAST(o_orderdate AS DATE)) AS BIGINT) AS W, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY model)"
GRID_SQL = (
    "(SELECT model, method, stated, d, r, greatest(d // per_column, 1) AS c, P, greatest(d // per_value, 1) AS k, W FROM "
    + MODELS_SQL + " AS m CROSS JOIN (VALUES " + ", ".join(f"('{m}', {s}, {r}::BIGINT, {c}::BIGINT, {k}::BIGINT, {p}::BIGINT)" for m, s, r, c, k, p in SHAPES) + ") AS s(method, stated, r, per_column, per_value, P)) AS g"
)


def models(spark, d):
    """model, d, W, n: the update vector of each month of orders has a coordinate for each customer and a worker for each day; n updates."""
    o = load_table(spark, d, "orders")
    month = (F.year("o_orderdate") * 100 + F.month("o_orderdate")).cast("int")
    return o.groupBy(month.alias("model")).agg(F.countDistinct("o_custkey").alias("d"), F.countDistinct(F.to_date("o_orderdate")).alias("W"), F.count("*").alias("n"))


def grid(spark, d):
    """Every shape for every month: model, method, stated, d, r, c, P, k, W."""
    shapes = spark.createDataFrame(SHAPES, "method string, stated boolean, r long, per_column long, per_value long, P long")
    share = lambda by: F.greatest(F.expr(f"d div {by}"), F.lit(1).cast("long"))
    return models(spark, d).crossJoin(F.broadcast(shapes)).select("model", "method", "stated", "d", "r", share("per_column").alias("c"), "P", share("per_value").alias("k"), "W")


SIZES = ["d", "r", "c", "P", "k", "W"]


def cols(*names: str):
    return (F.col(n) for n in names)


def union_cap(k, workers, d):
    """``cost.local_union_cap`` of columns."""
    return F.least(k * workers, d)


@query(
    "comm_table",
    f"""SELECT * FROM (
    SELECT model, method, d, r, c, P, k, W, r * c + P * k + k AS numbers, round(2 * d / CAST(r * c + P * k + k AS DOUBLE), 6) AS factor FROM {GRID_SQL}
    UNION ALL SELECT model, method || '_dense', d, r, c, P, k, W, 2 * d, 1.0::DOUBLE FROM {GRID_SQL}
    UNION ALL SELECT model, method || '_true_top_k', d, r, c, P, k, W, d + k, round(2 * d / CAST(d + k AS DOUBLE), 6) FROM {GRID_SQL}
    UNION ALL SELECT model, method || '_local_top_k', d, r, c, P, k, W, k + least(k * W, d), round(2 * d / CAST(k + least(k * W, d) AS DOUBLE), 6) FROM {GRID_SQL})""",
)
def comm_table(spark, d):
    n, r, c, p, k, w = cols(*SIZES)
    numbers = {"": C.comm_sketch(r, c, p, k), "_dense": C.comm_dense(n), "_true_top_k": C.comm_true_top_k(n, k), "_local_top_k": C.comm_local(k, union_cap(k, w, n))}
    each = F.explode(F.array(*(F.struct(F.lit(m).alias("of"), x.cast("long").alias("numbers")) for m, x in numbers.items())))
    rows = grid(spark, d).withColumn("x", each)
    return rows.select("model", F.concat("method", "x.of").alias("method"), *SIZES, "x.numbers", F.round(C.comm_dense(n) / F.col("x.numbers"), 6).alias("factor"))


@query("paper_compression", f"SELECT model, method, r, c, P, round(2 * d / CAST(r * c + P * k + k AS DOUBLE), 1) AS factor, round(r * c / CAST(P * k AS DOUBLE), 6) AS ratio FROM {GRID_SQL} WHERE stated")
def paper_compression(spark, d):
    n, r, c, p, k = cols("d", "r", "c", "P", "k")
    return grid(spark, d).where("stated").select("model", "method", "r", "c", "P", F.round(C.compression(n, r, c, p, k), 1).alias("factor"), F.round(C.round_ratio(r, c, p, k), 6).alias("ratio"))


WS = [1, 4, 16, 64, 256]


@query(
    "comm_vs_workers",
    f"""SELECT model, v.W, r * c + P * k + k AS sketch, k + least(k * v.W, d) AS local_top_k, 2 * d AS dense
    FROM {GRID_SQL} CROSS JOIN (VALUES {", ".join(f"({w})" for w in WS)}) AS v(W) WHERE method = 'language_20x'""",
)
def comm_vs_workers(spark, d):
    n, r, c, p, k, w = cols(*SIZES)
    rows = grid(spark, d).where("method = 'language_20x'").withColumn("W", F.explode(F.array(*map(F.lit, WS))))
    return rows.select("model", "W", C.comm_sketch(r, c, p, k).cast("long").alias("sketch"), C.comm_local(k, union_cap(k, w, n)).alias("local_top_k"), C.comm_dense(n).alias("dense"))


def _side(d: str, k: str) -> str:
    rows = f"CAST(ceil(ln({d} / 0.01::DOUBLE)) AS BIGINT)"
    return f"({rows} + 1 - {rows} % 2) * 4 * {k} + 5 * {k}"


@query(
    "asymptotic_table",
    f"""WITH g AS (SELECT model, d, 100 * d AS big, greatest(d // 1000, 1) AS k FROM {MODELS_SQL}), t AS (
    SELECT model, 'dense' AS method, 2 * d AS a, 2 * big AS b, 2 * d AS c FROM g UNION ALL SELECT model, 'true_top_k', d + k, big + k, d + k FROM g
    UNION ALL SELECT model, 'local_top_k', k + least(16 * k, d), k + least(16 * k, big), k + least(256 * k, d) FROM g
    UNION ALL SELECT model, 'sketch', {_side("d", "k")}, {_side("big", "k")}, {_side("d", "k")} FROM g)
    SELECT model, method, round(b / CAST(a AS DOUBLE), 6) AS by_parameters, round(c / CAST(a AS DOUBLE), 6) AS by_workers FROM t""",
)
def asymptotic_table(spark, d):
    """Growth of the numbers a worker sends and gets, from each month's vector: 100 times the parameters, 16 times the workers (16 to 256)."""
    n, big, k, p = F.col("d"), F.col("d") * 100, F.greatest(F.expr("d div 1000"), F.lit(1).cast("long")), 4
    odd = lambda x: x + 1 - x % 2
    sketch = lambda x, w: C.comm_sketch(odd(F.ceil(F.log(x / 0.01))), 4 * k, p, k)
    costs = {"dense": lambda x, w: C.comm_dense(x), "true_top_k": lambda x, w: C.comm_true_top_k(x, k), "local_top_k": lambda x, w: C.comm_local(k, union_cap(k, w, x)), "sketch": sketch}
    each = F.explode(F.array(*(F.struct(F.lit(m).alias("method"), F.round(f(big, 16) / f(n, 16), 6).alias("by_parameters"), F.round(f(n, 256) / f(n, 16), 6).alias("by_workers")) for m, f in costs.items())))
    return models(spark, d).select("model", each.alias("x")).select("model", "x.*")


@query("merge_measured")
def merge_measured(spark, d):
    """Records and bytes that merging the sketches of 4, 16 and 64 workers exchanged, by the metrics of its stages, and the most there can be."""
    from gradsift.operators import sketch as S
    from gradsift.plans.durable import commit
    from gradsift.plans.measure import exchanged
    from gradsift.workloads import fixtures as X

    rows = []
    for w in (4, 16, 64):
        cells = commit(S.sketch(X.signed_part_revenue(spark, d, w), X.FAM, by=["worker"]), "cells")
        records, size = map(sum, zip(*exchanged(S.merge(cells)), strict=True))
        rows.append((w, records, size, w * X.FAM.rows * X.FAM.cols))
    return spark.createDataFrame(rows, "W int, records long, bytes long, most long")


@query(
    "comm_quantised",
    f"""SELECT model, method, b AS cell_bits, r * c * b / 32.0::DOUBLE + P * k + k AS numbers, round(2 * d / (r * c * b / 32.0::DOUBLE + P * k + k), 6) AS factor
    FROM {GRID_SQL} CROSS JOIN (VALUES (16), (32)) AS t(b)""",
)
def comm_quantised(spark, d):
    n, r, c, p, k, bits = cols("d", "r", "c", "P", "k", "cell_bits")
    rows = grid(spark, d).withColumn("cell_bits", F.explode(F.array(F.lit(16), F.lit(32))))
    return rows.select("model", "method", "cell_bits", C.comm_sketch(r, c, p, k, bits).alias("numbers"), F.round(C.compression(n, r, c, p, k, bits), 6).alias("factor"))


@query(
    "effective_compression",
    f"""SELECT model, method, round(factor, 6) AS factor, iterations, round(factor / iterations, 6) AS effective FROM (SELECT *, 2 * d / CAST(r * c + P * k + k AS DOUBLE) AS factor FROM {GRID_SQL})
    CROSS JOIN (VALUES (1.0::DOUBLE), (1.5), (2.0)) AS t(iterations)""",
)
def effective_compression(spark, d):
    factor = C.compression(*cols("d", "r", "c", "P", "k"))
    rows = grid(spark, d).withColumn("iterations", F.explode(F.array(*map(F.lit, (1.0, 1.5, 2.0)))))
    return rows.select("model", "method", F.round(factor, 6).alias("factor"), "iterations", F.round(C.effective_compression(factor, F.col("iterations")), 6).alias("effective"))


TS = [1, 10, 100]


@query(
    "bounds_table",
    f"""SELECT model, method, T, k, d, round(0.5 / (0.1 * T), 9) AS term1, round(power(d / k, 2) * 4 * 2 / (0.01 * T * T), 9) AS term2, round(power(d / k, 3) * 8 / (0.1 * T * T * T), 9) AS term3,
    round(power(d / k, 2), 6) AS crossover, round(4 * 2 / (0.1 * T), 9) AS sgd
    FROM (SELECT m.model, method, CAST(m.n * t AS DOUBLE) AS T, CAST(k AS DOUBLE) AS k, CAST(g.d AS DOUBLE) AS d FROM {GRID_SQL} JOIN {MODELS_SQL} AS m ON m.model = g.model CROSS JOIN (VALUES {", ".join(f"({t})" for t in TS)}) AS a(t) WHERE stated)""",
)
def bounds_table(spark, d):
    """Terms for variance 0.5, moment bound 2, curvature 0.1 to 2; a step for each order of the month, in 1, 10 and 100 passes."""
    rows = grid(spark, d).where("stated").join(models(spark, d).select("model", "n"), "model").withColumn("t", F.explode(F.array(*map(F.lit, TS))))
    rows = rows.select("model", "method", (F.col("n") * F.col("t")).cast("double").alias("T"), F.col("k").cast("double").alias("k"), F.col("d").cast("double").alias("d"))
    t, k, n = cols("T", "k", "d")
    terms = B.bound_distributed(t, n, k, 0.5, 2.0, 0.1, 2.0)
    terms = [F.round(x, 9).alias(f"term{i}") for i, x in enumerate(terms, 1)]
    return rows.select("model", "method", "T", "k", "d", *terms, F.round(B.crossover_steps(n, k), 6).alias("crossover"), F.round(B.bound_sgd(t, 2.0, 0.1, 2.0), 9).alias("sgd"))


@query(
    "step_time_table",
    f"""SELECT W, round(1024.0::DOUBLE / W * 0.001, 9) AS compute, round(n * 4.0::DOUBLE / 1e9, 9) AS comm, round(greatest(1024.0::DOUBLE / W * 0.001, n * 4.0::DOUBLE / 1e9), 9) AS floor, method
    FROM (VALUES {", ".join(f"({w})" for w in WS)}) AS t(W) CROSS JOIN (VALUES ('dense', 180000000), ('sketch', 4400000)) AS m(method, n)""",
)
def step_time_table(spark, d):
    """Floor of a step: compute falls with the workers, communication does not."""
    rows = []
    for w in WS:
        for name, n in (("dense", C.comm_dense(90_000_000)), ("sketch", C.comm_sketch(15, 180_000, 16, 100_000))):
            rows.append((w, *(round(x, 9) for x in C.step_time(1024, w, 1e9, n, 1e12, 1e9)), name))
    return spark.createDataFrame(rows, "W int, compute double, comm double, floor double, method string")


@query("theory_bits_table", "SELECT d, W, round(100 * log2(d * 1000.0::DOUBLE / 0.01) * W, 3) AS bits FROM (VALUES (1000000.0::DOUBLE), (1000000000.0)) AS a(d) CROSS JOIN (VALUES (1), (256)) AS b(W)")
def theory_bits_table(spark, d):
    rows = [(float(n), w, round(C.theory_bits(100, n, 1000, 0.01, w), 3)) for n in (10**6, 10**9) for w in (1, 256)]
    return spark.createDataFrame(rows, "d double, W int, bits double")


@query(
    "min_offset_table",
    f"""SELECT model, method, d, k, b AS beta, round(2 + d * (1 + b) / (k * (1 + 4 * b / ((b - 4) * power(b + 1, 2)))), 6) AS offset_
    FROM (SELECT model, method, CAST(d AS DOUBLE) AS d, CAST(k AS DOUBLE) AS k FROM {GRID_SQL}) CROSS JOIN (VALUES (5.0::DOUBLE), (8.0)) AS u(b)""",
)
def min_offset_table(spark, d):
    n, k = (F.col(x).cast("double") for x in ("d", "k"))
    each = F.explode(F.array(*(F.struct(F.lit(b).alias("beta"), F.round(B.min_offset(n, k, b), 6).alias("offset_")) for b in (5.0, 8.0))))
    return grid(spark, d).select("model", "method", n.alias("d"), k.alias("k"), each.alias("x")).select("model", "method", "d", "k", "x.*")


PAIRS = """SELECT a.doc_id AS pair_id, string_split(a.text, ' ') AS candidate, string_split(b.text, ' ') AS reference
 FROM (SELECT doc_id, lang, text, substr(text, 1, 40) AS k, row_number() OVER (PARTITION BY lang, substr(text, 1, 40) ORDER BY doc_id) AS n FROM documents) a
 JOIN (SELECT lang, text, substr(text, 1, 40) AS k, row_number() OVER (PARTITION BY lang, substr(text, 1, 40) ORDER BY doc_id) AS n FROM documents) b
 ON a.lang = b.lang AND a.k = b.k AND b.n = a.n - 1"""


def _gram(side: str, n: int) -> str:
    word = lambda j: f"list_extract({side}, i + {j})"
    return f"SELECT pair_id, {n} AS n, {(chr(32).join(['', '||', repr(' '), '||', ''])).join(word(j) for j in range(n))} AS g FROM (SELECT pair_id, {side}, unnest(range(1, len({side}) - {n - 2})) AS i FROM p)"


BLEU_SQL = f"""
WITH p AS ({PAIRS}),
c AS (SELECT pair_id, n, g, count(*) AS c FROM ({" UNION ALL ".join(_gram("candidate", n) for n in range(1, 5))}) GROUP BY pair_id, n, g),
r AS (SELECT pair_id, n, g, count(*) AS r FROM ({" UNION ALL ".join(_gram("reference", n) for n in range(1, 5))}) GROUP BY pair_id, n, g),
m AS (SELECT c.n, CAST(sum(least(c.c, coalesce(r.r, 0))) AS BIGINT) AS matched, CAST(sum(c.c) AS BIGINT) AS total FROM c LEFT JOIN r ON c.pair_id = r.pair_id AND c.n = r.n AND c.g = r.g GROUP BY c.n),
l AS (SELECT CAST(sum(len(candidate)) AS DOUBLE) AS c, CAST(sum(len(reference)) AS DOUBLE) AS r FROM p),
s AS (SELECT exp(sum(ln(matched / CAST(total AS DOUBLE))) / 4) AS s FROM m)
SELECT n, matched, total, round(CASE WHEN l.c >= l.r THEN 1.0 ELSE exp(1 - l.r / l.c) END, 6) AS brevity,
 round(s.s * (CASE WHEN l.c >= l.r THEN 1.0 ELSE exp(1 - l.r / l.c) END) * 100, 6) AS score FROM m CROSS JOIN l CROSS JOIN s
"""


@query("bleu_pairs", BLEU_SQL)
def bleu_pairs(spark, d):
    """Corpus BLEU of the whole texts of document copies, paired by language and the first 40 characters."""
    from pyspark.sql import Window

    docs = load_table(spark, d, "documents").select("doc_id", "lang", "text", F.substring("text", 1, 40).alias("k"))
    w = Window.partitionBy("lang", "k").orderBy("doc_id")
    pairs = docs.withColumn("ref", F.lag("text").over(w)).where("ref is not null")
    pairs = pairs.select(F.col("doc_id").alias("pair_id"), F.split("text", " ").alias("candidate"), F.split("ref", " ").alias("reference"))
    return corpus_bleu(pairs)


@query("rounds_table", "SELECT * FROM (VALUES ('dense', 1), ('true_top_k', 1), ('local_top_k', 1), ('sketch_no_refetch', 1), ('sketch', 2), ('random_candidates', 2), ('annealed', 2)) AS t(method, rounds)")
def rounds_table(spark, d):
    names = ["dense", "true_top_k", "local_top_k", "sketch_no_refetch", "sketch", "random_candidates", "annealed"]
    return spark.createDataFrame([(n, C.rounds(n)) for n in names], "method string, rounds int")


@query("size_table", "SELECT k, d, t AS steps, CAST(r + 1 - r % 2 AS INTEGER) AS r, 4 * k AS c FROM (SELECT k, d, t, CAST(ceil(ln(d * t / 0.01::DOUBLE)) AS BIGINT) AS r FROM (VALUES (100, 1000000::BIGINT), (1000, 90000000::BIGINT)) AS a(k, d) CROSS JOIN (VALUES (1), (1000)) AS b(t))")
def size_table(spark, d):
    """Rows and columns for top-k recovery with failure probability 0.01."""
    from gradsift.operators.sketch import size_for

    rows = [(k, n, t, *size_for(k, n, 0.01, t)) for k, n in ((100, 1_000_000), (1000, 90_000_000)) for t in (1, 1000)]
    return spark.createDataFrame(rows, "k int, d long, steps int, r int, c int")


@query("index_cost_table", f"SELECT model, method, r * c + P * k + k + (P * k + k) * CAST(ceil(log2(d)) AS BIGINT) / 32.0::DOUBLE AS numbers FROM {GRID_SQL}")
def index_cost_table(spark, d):
    """Costs with the names of requested and updated coordinates counted too."""
    n, r, c, p, k = cols("d", "r", "c", "P", "k")
    return grid(spark, d).select("model", "method", C.comm_sketch(r, c, p, k, d=n, include_indices=True, bits=F.when(n > 1, F.length(F.bin(n - 1))).otherwise(0)).alias("numbers"))
