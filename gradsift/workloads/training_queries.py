"""One and three training steps on the regression examples, checked against unrolled SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from gradsift.operators import losses as L
from gradsift.operators import recover as R
from gradsift.operators import trainers as T
from gradsift.operators.hashing import HashFamily
from gradsift.sources.tables import load_table
from gradsift.workloads import fixtures as X
from gradsift.workloads.registry import query
from gradsift.workloads.relational_queries import TRIGRAM_SQL, document_trigrams

D, K, P, W, L2, XI = X.DIM, 3, 2, 4, 0.01, 10.0
ETA, M, LOCAL_K = 0.05, 0.9, 2
FAM8 = HashFamily(rows=5, cols=16, seed=42)


def w0(spark):
    return T.initial_weights(spark, D, seed=2, scale=0.5)


W0_SQL = f"SELECT i AS coord, ({R.sql_shuffle_key('i', 2)} % 2001 - 1000) / 1000.0::DOUBLE * 0.5::DOUBLE AS w FROM (SELECT unnest(range(0, {D})) AS i)"
BASE = [("ex", X.ridge_long_sql(W)), ("n", "SELECT worker, count(DISTINCT ex_id) AS n FROM ex GROUP BY worker"), ("w0", W0_SQL)]
SLOPES = {"ridge": "z.z - e.y", "logistic": "1 / (1 + exp(-z.z)) - (CASE WHEN e.y > 2 THEN 1.0 ELSE 0.0 END)"}


def gradient_sql(w: str, loss: str = "ridge", l2: float = L2) -> str:
    return f"""SELECT e.worker, e.coord, sum(({SLOPES[loss]}) * e.val) / n.n + {l2}::DOUBLE * max(w.w) AS g FROM ex e
     JOIN (SELECT e.ex_id, sum(e.val * w.w) AS z FROM ex e JOIN {w} w ON e.coord = w.coord GROUP BY e.ex_id) z ON e.ex_id = z.ex_id
     JOIN n ON e.worker = n.worker JOIN {w} w ON e.coord = w.coord GROUP BY e.worker, e.coord, n.n"""


def chain(ctes: list[tuple[str, str]], final: str) -> str:
    return "WITH " + ", ".join(f"{n} AS MATERIALIZED ({q})" for n, q in ctes) + " " + final



def r6(c: str):
    return (F.round(F.col(c), 6) + F.lit(0.0)).alias(c)


GRADIENT = "SELECT worker, coord, round(g, 6) + 0.0 AS g FROM g"


@query("gradient_ridge_by_worker", chain([*BASE, ("g", gradient_sql("w0"))], GRADIENT))
def gradient_ridge_by_worker(spark, d):
    return L.RidgeLoss(L2).gradient(X.ridge_examples(spark, d, W), w0(spark), D).select("worker", "coord", r6("g"))


def logit_examples(spark, d):
    return X.ridge_examples(spark, d, W).withColumn("y", F.when(F.col("y") > 2, 1.0).otherwise(0.0))


@query("gradient_logistic_by_worker", chain([*BASE, ("g", gradient_sql("w0", "logistic"))], GRADIENT))
def gradient_logistic_by_worker(spark, d):
    return L.LogisticLoss(L2).gradient(logit_examples(spark, d), w0(spark), D).select("worker", "coord", r6("g"))


LANGS = ["de", "en", "es", "fr"]


def language_examples(spark, d, buckets: int = 256, workers: int = 4):
    """Language of a document from normalised counts of the hashed trigrams of its whole text."""
    total = F.aggregate("n", F.lit(0).cast("long"), lambda a, b: a + b)
    t = document_trigrams(spark, d, buckets).where(F.size("n") > 0).withColumn("total", total)
    x = t.select("doc_id", F.zip_with("coord", "n", lambda c, n: F.struct(c.alias("coord"), (n / F.col("total") * 10).alias("val"))).alias("x"))
    docs = load_table(spark, d, "documents").select("doc_id", "lang").where(F.col("lang").isin(LANGS))
    y = sum((F.when(F.col("lang") == x, i).otherwise(0) for i, x in enumerate(LANGS)), F.lit(0))
    return docs.join(x, "doc_id").select(F.col("doc_id").alias("ex_id"), (F.col("doc_id") % workers).cast("int").alias("worker"), y.alias("y"), "x")


SOFTMAX = f"""
WITH t AS MATERIALIZED (SELECT doc_id, coord % 256 AS f, count(*) AS n FROM ({TRIGRAM_SQL}) GROUP BY 1, 2),
ex AS MATERIALIZED (SELECT t.doc_id, CAST(t.doc_id % 4 AS INTEGER) AS worker, CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS y, f, n / CAST(sum(n) OVER (PARTITION BY t.doc_id) AS DOUBLE) * 10 AS val
 FROM t JOIN documents d ON t.doc_id = d.doc_id WHERE lang IN ('de', 'en', 'es', 'fr')),
n AS (SELECT worker, count(DISTINCT doc_id) AS n FROM ex GROUP BY worker),
w AS MATERIALIZED (SELECT i AS coord, ({R.sql_shuffle_key('i', 2)} % 2001 - 1000) / 1000.0::DOUBLE * 0.5::DOUBLE AS w FROM (SELECT unnest(range(0, 1024)) AS i)),
z AS MATERIALIZED (SELECT doc_id, worker, y, c, sum(val * w) AS z FROM ex CROSS JOIN (VALUES (0), (1), (2), (3)) AS k(c) JOIN w ON w.coord = f * 4 + c GROUP BY doc_id, worker, y, c),
p AS MATERIALIZED (SELECT doc_id, c, exp(z) / sum(exp(z)) OVER (PARTITION BY doc_id) - (CASE WHEN c = y THEN 1.0::DOUBLE ELSE 0.0 END) AS e FROM z)
SELECT ex.worker, f * 4 + c AS coord, round(sum(e * val) / n.n, 6) + 0.0 AS g FROM ex JOIN p ON ex.doc_id = p.doc_id JOIN n ON ex.worker = n.worker GROUP BY ex.worker, f * 4 + c, n.n
"""


@query("gradient_softmax_by_worker", SOFTMAX)
def gradient_softmax_by_worker(spark, d):
    return L.SoftmaxLoss(4).gradient(language_examples(spark, d), T.initial_weights(spark, 1024, seed=2, scale=0.5), 1024).select("worker", "coord", r6("g"))


MOMENTS = """SELECT count(*) AS W, round(avg(n2), 6) AS g2, round(avg(n2) - max(m2), 6) AS var FROM (SELECT worker, sum(g * g) AS n2 FROM g GROUP BY worker)
 CROSS JOIN (SELECT sum(s * s) AS m2 FROM (SELECT coord, sum(g) / (SELECT count(*) FROM n) AS s FROM g GROUP BY coord))"""


@query("gradient_moments", chain([*BASE, ("g", gradient_sql("w0"))], MOMENTS))
def gradient_moments(spark, d):
    g = L.RidgeLoss(L2).gradient(X.ridge_examples(spark, d, W), w0(spark), D)
    return L.grad_moments(g).select("W", F.round("g2", 6).alias("g2"), F.round("var", 6).alias("var"))


# annealed trainer -------------------------------------------------------------


def cells_ctes(t: int, v: str) -> list[tuple[str, str]]:
    """Mean sketch of v(worker, coord, delta), its estimates and its norm at step t."""
    return [
        (f"cells{t}", f"SELECT row, bucket, sum(delta * sign) / {W}.0::DOUBLE AS cell FROM ({FAM8.sql_cells(v, keep='worker, coord, delta')}) GROUP BY row, bucket"),
        (f"est{t}", f"SELECT a.coord, median(a.sign * coalesce(c.cell, 0.0)) AS est FROM ({FAM8.sql_cells('w0', keep='coord')}) a LEFT JOIN cells{t} c ON a.row = c.row AND a.bucket = c.bucket GROUP BY a.coord"),
        (f"norm{t}", f"SELECT median(s) AS norm2 FROM (SELECT row, sum(cell * cell) AS s FROM cells{t} GROUP BY row)"),
    ]


def annealed_ctes(steps: int) -> list[tuple[str, str]]:
    out = list(BASE)
    for t in range(1, steps + 1):
        w = f"w{t - 1}"
        out.append((f"g{t}", gradient_sql(w)))
        eta = f"{1.0 / (t + XI)!r}::DOUBLE"
        if t == 1:
            out.append(("v1", f"SELECT worker, coord, g * {eta} AS delta FROM g1"))
        else:
            out.append((f"v{t}", f"SELECT worker, coord, coalesce(g, 0) * {eta} + coalesce(a, 0) AS delta FROM g{t} FULL JOIN a{t - 1} USING (worker, coord)"))
        out += cells_ctes(t, f"v{t}")
        out.append((f"p{t}", f"SELECT coord FROM (SELECT *, row_number() OVER (ORDER BY is_heavy DESC, CASE WHEN is_heavy THEN abs(est) END DESC NULLS LAST, {R.sql_shuffle_key('coord', 0, t)}, coord) AS r FROM (SELECT coord, est, est * est >= norm2 / {K} AS is_heavy FROM est{t} CROSS JOIN norm{t})) WHERE r <= {K}"))
        out.append((f"u{t}", f"SELECT p.coord, coalesce(sum(delta), 0) / {W}.0::DOUBLE AS exact FROM p{t} p LEFT JOIN v{t} v ON p.coord = v.coord GROUP BY p.coord"))
        out.append((f"w{t}", f"SELECT w.coord, w.w - coalesce(u.exact, 0) AS w FROM {w} w LEFT JOIN u{t} u ON w.coord = u.coord"))
        out.append((f"a{t}", f"SELECT v.worker, v.coord, v.delta - coalesce(u.exact, 0) AS a FROM v{t} v LEFT JOIN u{t} u ON v.coord = u.coord"))
    return out


def annealed(spark, d, steps, output="last"):
    return T.train_annealed(X.ridge_examples(spark, d, W), L.RidgeLoss(L2), D, K, XI, steps, W, FAM8, w0(spark), output=output)


def _annealed_rows(spark, d, steps):
    run = annealed(spark, d, steps)
    return run.state.join(run.w, "coord").select("worker", "coord", r6("w"), r6("a"))


def _annealed_sql(t):
    return chain(annealed_ctes(t), f"SELECT a.worker, a.coord, round(w.w, 6) + 0.0 AS w, round(a.a, 6) + 0.0 AS a FROM a{t} a JOIN w{t} w ON a.coord = w.coord")


query("annealed_step1", _annealed_sql(1))(lambda spark, d: _annealed_rows(spark, d, 1))
query("annealed_steps3", _annealed_sql(3))(lambda spark, d: _annealed_rows(spark, d, 3))
_Q = [(XI + t) ** 2 for t in (1, 2, 3)]
WEIGHTED = f"SELECT w0.coord, round(({_Q[0]}::DOUBLE * w0.w + {_Q[1]}::DOUBLE * w1.w + {_Q[2]}::DOUBLE * w2.w) / {sum(_Q)}::DOUBLE, 6) + 0.0 AS w_bar FROM w0 JOIN w1 ON w0.coord = w1.coord JOIN w2 ON w0.coord = w2.coord"


@query("annealed_weighted_output", chain(annealed_ctes(3), WEIGHTED))
def annealed_weighted_output(spark, d):
    return annealed(spark, d, 3, "weighted").w.select("coord", (F.round("w", 6) + F.lit(0.0)).alias("w_bar"))


# momentum trainer and baselines -----------------------------------------------


DENSE_BELOW = 2  # coordinates that the run with groups sends in full


def momentum_ctes(steps: int, method: str = "sketch", mask: bool = True, variant: str = "") -> list[tuple[str, str]]:
    """Every step as common table expressions; ``variant`` names one changed rule."""
    out = list(BASE)
    for t in range(1, steps + 1):
        w = f"w{t - 1}"
        out.append((f"g{t}", gradient_sql(w)))
        add = "g" if variant == "no_correction" else f"({M}::DOUBLE * s.u + g)"
        kept = "0" if variant == "no_accumulation" else "s.v"
        old = f"SELECT worker, coord, {M}::DOUBLE * s.u + g AS u, {kept} + {add} AS delta FROM g{t} JOIN s{t - 1} s USING (worker, coord)"
        out.append((f"v{t}", "SELECT worker, coord, g AS u, g AS delta FROM g1" if t == 1 else old))
        top = lambda q, col, k: f"SELECT * FROM (SELECT *, row_number() OVER (ORDER BY abs({col}) DESC, coord) AS r FROM ({q})) WHERE r <= {k}"
        source = f"(SELECT * FROM v{t} WHERE coord >= {DENSE_BELOW})" if variant == "groups" else f"v{t}"
        total = f"SELECT coord, sum(delta) AS exact FROM {source} GROUP BY coord"
        on = "v.coord = u.coord"
        if method == "sketch":
            ctes = cells_ctes(t, source)
            if variant == "sixteen_bits":
                step = f"(SELECT max(abs(cell)) / 32767 FROM raw{t})"
                ctes = [(f"raw{t}", ctes[0][1]), (f"cells{t}", f"SELECT row, bucket, CAST(round(cell / {step}) AS SMALLINT) * {step} AS cell FROM raw{t}"), *ctes[1:]]
            out += ctes
            asked = f"SELECT coord FROM ({top(f'SELECT * FROM est{t}', 'est', P * K)})"
            update = f"SELECT coord, exact FROM ({top(f'SELECT * FROM ({total}) WHERE coord IN ({asked})', 'exact', K)})"
            if variant == "no_refetch":
                update = f"SELECT coord, est * {W} AS exact FROM ({top(f'SELECT * FROM est{t}', 'est', K)})"
            if variant == "groups":
                update += f" UNION ALL SELECT coord, sum(delta) AS exact FROM v{t} WHERE coord < {DENSE_BELOW} GROUP BY coord"
            out.append((f"u{t}", update))
        elif method == "random_candidates":
            asked = f"SELECT coord FROM w0 ORDER BY {R.sql_shuffle_key('coord', 0, t)}, coord LIMIT {P * K}"
            out.append((f"u{t}", f"SELECT coord, exact FROM ({top(f'SELECT * FROM ({total}) WHERE coord IN ({asked})', 'exact', K)})"))
        elif method == "true_top_k":
            out.append((f"u{t}", f"SELECT coord, exact FROM ({top(total, 'exact', K)})"))
        elif method == "dense":
            out.append((f"u{t}", total))
        else:
            out.append((f"sent{t}", f"SELECT worker, coord, delta AS exact FROM (SELECT *, row_number() OVER (PARTITION BY worker ORDER BY abs(delta) DESC, coord) AS r FROM v{t}) WHERE r <= {LOCAL_K}"))
            out.append((f"u{t}", f"SELECT coord, sum(exact) AS exact FROM sent{t} GROUP BY coord"))
            on = "v.worker = u.worker AND v.coord = u.coord"
        keep_u = "v.u" if not mask or method == "dense" else "CASE WHEN u.coord IS NULL THEN v.u ELSE 0 END"
        src = f"sent{t}" if method == "local_top_k" else f"u{t}"
        left = f"v.delta - u.exact / {W}" if variant == "subtract" else "0"
        out.append((f"s{t}", f"SELECT v.worker, v.coord, {keep_u} AS u, CASE WHEN u.coord IS NULL THEN v.delta ELSE {left} END AS v FROM v{t} v LEFT JOIN {src} u ON {on}"))
        step = f"u{t}"
        if variant == "no_correction":
            step = f"vel{t}"
            old = f" FULL JOIN vel{t - 1} p ON u.coord = p.coord" if t > 1 else ""
            out.append((step, f"SELECT coalesce(u.coord, {'p.coord' if t > 1 else 'NULL'}) AS coord, coalesce(u.exact, 0) + {f'{M}::DOUBLE * coalesce(p.exact, 0)' if t > 1 else '0'} AS exact FROM u{t} u{old}"))
        rate, share = (f"({ETA}::DOUBLE / {t})" if variant == "schedule" else f"{ETA}::DOUBLE"), (f" / {W}" if variant == "mean" else "")
        out.append((f"w{t}", f"SELECT w.coord, w.w - {rate} * coalesce(u.exact, 0){share} AS w FROM {w} w LEFT JOIN {step} u ON w.coord = u.coord"))
    return out


def momentum(spark, d, steps, method="sketch", **more):
    k = LOCAL_K if method == "local_top_k" else K
    return T.train_momentum(X.ridge_examples(spark, d, W), L.RidgeLoss(L2), D, k, steps, W, more.pop("eta", ETA), M, P, FAM8, method, w0(spark), **more)


def _momentum_rows(spark, d, steps, **more):
    run = momentum(spark, d, steps, **more)
    return run.state.join(run.w, "coord").select("worker", "coord", r6("w"), r6("u"), r6("v"))


def _momentum_sql(t, mask=True):
    return chain(momentum_ctes(t, mask=mask), f"SELECT s.worker, s.coord, round(w.w, 6) + 0.0 AS w, round(s.u, 6) + 0.0 AS u, round(s.v, 6) + 0.0 AS v FROM s{t} s JOIN w{t} w ON s.coord = w.coord")


query("momentum_step1", _momentum_sql(1))(lambda spark, d: _momentum_rows(spark, d, 1))
query("momentum_steps3", _momentum_sql(3))(lambda spark, d: _momentum_rows(spark, d, 3))
query("momentum_steps3_nomask", _momentum_sql(3, False))(lambda spark, d: _momentum_rows(spark, d, 3, mask_velocity=False))
for _name, _method in (("dense_steps3", "dense"), ("true_topk_steps3", "true_top_k"), ("local_topk_steps3", "local_top_k")):
    query(_name, chain(momentum_ctes(3, _method), "SELECT coord, round(w, 6) + 0.0 AS w FROM w3"))(
        lambda spark, d, method=_method: momentum(spark, d, 3, method).w.select("coord", r6("w"))
    )



def dense_group(spark):
    return spark.createDataFrame([(0, DENSE_BELOW, "first", False)], "lo long, hi long, name string, compressed boolean")


#: Rules of the momentum trainer that one run each changes.
VARIANTS = {
    "no_correction": lambda spark: {"momentum_correction": False},
    "no_accumulation": lambda spark: {"accumulate": False},
    "subtract": lambda spark: {"residual": "subtract"},
    "schedule": lambda spark: {"eta": lambda t: ETA / t},
    "groups": lambda spark: {"groups": dense_group(spark)},
    "sixteen_bits": lambda spark: {"cell_bits": 16},
    "no_refetch": lambda spark: {"refetch": False},
    "mean": lambda spark: {"reduce": "mean"},
}
for _name, _more in VARIANTS.items():
    query(f"momentum_steps3_{_name}", chain(momentum_ctes(3, variant=_name), "SELECT s.worker, s.coord, round(w.w, 6) + 0.0 AS w, round(s.u, 6) + 0.0 AS u, round(s.v, 6) + 0.0 AS v FROM s3 s JOIN w3 w ON s.coord = w.coord"))(
        lambda spark, d, more=_more: _momentum_rows(spark, d, 3, **more(spark))
    )
query("random_candidates_steps3", chain(momentum_ctes(3, "random_candidates"), "SELECT coord, round(w, 6) + 0.0 AS w FROM w3"))(lambda spark, d: momentum(spark, d, 3, "random_candidates").w.select("coord", r6("w")))

BALANCE = f"""SELECT 'subtract' AS rule, coord, round(lhs, 6) + 0.0 AS lhs, round(rhs, 6) + 0.0 AS rhs FROM
 (SELECT coord, sum(delta) / {W}.0::DOUBLE AS lhs FROM v3 GROUP BY coord) JOIN (SELECT a.coord, sum(a.a) / {W}.0::DOUBLE + coalesce(max(u.exact), 0) AS rhs FROM a3 a LEFT JOIN u3 u ON a.coord = u.coord GROUP BY a.coord) USING (coord)"""


@query("residual_mass_balance", chain(annealed_ctes(3), BALANCE))
def residual_mass_balance(spark, d):
    """Mean corrected vector = update + mean new residual, coordinate by coordinate."""
    before = annealed(spark, d, 2)
    ex, loss = X.ridge_examples(spark, d, W), L.RidgeLoss(L2)
    v = T.commit(T.corrected(loss.gradient(ex, before.w, D), before.state, 1.0 / (3 + XI)), "v")
    cells = T.commit(T.S.merge(T.S.sketch(v, FAM8, by=["worker"]), "mean", W), "cells")
    update = T.commit(R.exact_refetch(v, R.heavy_or_random_picks(cells, FAM8, D, K, 0, 3), K, "mean", W), "update")
    a = T.subtract_update(v, update, spark.range(W).select(F.col("id").cast("int").alias("worker")))
    left = v.groupBy("coord").agg((F.sum("delta") / W).alias("lhs"))
    right = a.groupBy("coord").agg((F.sum("a") / W).alias("a")).join(update.select("coord", "exact"), "coord", "left")
    right = right.select("coord", (F.col("a") + F.coalesce("exact", F.lit(0.0))).alias("rhs"))
    return left.join(right, "coord").select(F.lit("subtract").alias("rule"), "coord", r6("lhs"), r6("rhs"))
