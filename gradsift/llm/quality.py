"""Quality rules by robust multivariate outliers, in DataFrame operations only.

Base counts come from array functions over each text.  Documents that pass the base rules get a
vector of transformed statistics in fixed point; per language and source a minimum covariance
determinant estimate is found.  Several starts (coordinate medians, and two subsets chosen by hash)
take two concentration steps each: the share ``coverage`` of rows with the smallest distance is kept,
centre and covariance are taken anew from them.  The start with the smallest determinant goes on
until its determinant no longer falls; a last step re-weights with the rows inside the 97.5 %
quantile.  A document is rejected when its squared Mahalanobis distance exceeds the quantile
``accept`` of the chi-square law.

A covariance is regularised as if ``PRIOR`` further rows had that of the language (which itself is
estimated in the same way, with a fixed diagonal as its prior), so small groups lean on their language
and large ones on their rows, by one formula at every size.  Each variance has a floor besides, as
most documents have no symbols or repeated lines at all.  Moments are exact sums of integers and
the kept share is cut by a histogram of distances, so every step is one aggregation over all rows,
equal for any partitioning.

Defined results: null or blank text has no words and fails the base rules; null language or source
is a group of its own; repeated rows get equal verdicts; a null id keeps its row; further columns
are kept by ``quality_verdicts`` only if asked for; an empty table gives an empty table.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm.common import materialise, maybe_broadcast, table

# White space and symbols of the rules.
SPACE, SYMBOLS = r"[\x20\x09-\x0D]+", r"[#*$%&|<>]"
UNIT = 1000
#: Statistic vector and the standard deviation added to each coordinate.
FLOORS = {"x_length": 0.30, "x_word": 0.30, "x_symbols": 0.60, "x_lines": 0.60, "x_repeats": 0.60}
X = list(FLOORS)
#: Rows that the prior covariance counts for, and rows that the language's centre counts for.
PRIOR, PRIOR_CENTRE = 50, 5
#: Concentration steps of every start, and most of the chosen one; a fall of the log determinant that ends them.
FIRST_STEPS, MOST_STEPS, FALL = 2, 12, 5e-3
KEYS = ["grp", "start"]


def chi2_cdf(x: float, k: float) -> float:
    """Chi-square distribution function by the series of the incomplete gamma function."""
    if x <= 0:
        return 0.0
    a, term, total, n = k / 2, 1.0, 1.0, 0
    while term > 1e-17 * total:
        n += 1
        term *= (x / 2) / (a + n)
        total += term
    return min(1.0, total * math.exp(a * math.log(x / 2) - x / 2 - math.lgamma(a + 1)))


def chi2_quantile(p: float, k: float) -> float:
    low, high = 0.0, 1000.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_cdf(mid, k) < p else (low, mid)
    return high


def base_counts(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda s: s.rlike(r"[^\x20\x09-\x0D]"))
    rows = docs.select(
        *keep,
        F.array_remove(F.split(text, SPACE), "").alias("_w"),
        (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines.alias("_l"),
    )
    rows = rows.select(
        *keep,
        "n_symbols",
        F.size("_w").cast("long").alias("n_words"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"),
    )
    n = F.size("_h")
    rows = rows.withColumn(
        "_g",
        F.when(
            n >= 3,
            F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get("_h", i), F.get("_h", i + 1), F.get("_h", i + 2))),
        ),
    ).drop("_h")
    # windows found twice are looked for only in texts that have any
    rows = rows.withColumn("_g", F.when(F.size(F.array_distinct("_g")) < F.size("_g"), F.col("_g")))
    rows = rows.withColumn("_s", F.sort_array(F.transform("_g", lambda g, i: F.struct(g.alias("g"), i.alias("i"))))).drop("_g")
    twice = F.filter(
        F.transform("_s", lambda x, k: F.struct(x["i"].alias("i"), ((x["g"] == F.get("_s", k - 1)["g"]) | (x["g"] == F.get("_s", k + 1)["g"])).alias("d"))),
        lambda x: x["d"],
    )
    covered = F.array_distinct(F.flatten(F.transform(twice, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2))))
    rows = rows.withColumn("n_repeat_words", F.coalesce(F.when(F.col("_s").isNotNull(), F.size(covered)), F.lit(0)).cast("long")).drop("_s")
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.select(*keep, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"))


def statistic_vector() -> list[Column]:
    """Transformed statistics in fixed point: logarithms of the length, of the mean word (changes by 1 for a letter at 5) and of counts per word."""
    n = F.greatest(F.col("n_words"), F.lit(1))
    per = lambda c: F.log1p(100.0 * F.col(c) / n)
    raw = [F.log1p("n_words"), 5 * F.log(F.greatest(F.col("word_chars"), F.lit(1)) / n), per("n_symbols"), per("n_dup_lines"), per("n_repeat_words")]
    return [F.round(c * UNIT).cast("long").alias(x) for c, x in zip(raw, X, strict=True)]


def _pairs() -> list[tuple[int, int]]:
    return [(i, j) for i in range(len(X)) for j in range(i + 1)]


def _estimate(rows: DataFrame, scale: float, prior: DataFrame, groups: int) -> DataFrame:
    """Per grp and start of rows: centre m0.., covariance v_i_j, Cholesky factor c_i_j with floors, log determinant.

    prior: (grp, rows p_n that its centre counts for, centre p_m0.., covariance p_v0_0..) of every grp,
    of which there are ``groups``.
    """
    # statistics stay below 2^17, so sums of products are exact for 2^29 rows of the largest values and 10^11 usual ones
    sums = ["cast(count(*) as double) as n", *(f"cast(sum({x}) as double) as s{i}" for i, x in enumerate(X))]
    sums += [f"cast(sum({X[i]} * {X[j]}) as double) as s{i}_{j}" for i, j in _pairs()]
    g = rows.groupBy(*KEYS).agg(*map(F.expr, sums)).join(maybe_broadcast(prior, groups, 100_000), "grp")
    mean = [f"s{i} / n / {UNIT}" for i in range(len(X))]
    cov = [f"(n * {scale!r}D * (s{i}_{j} / n / {UNIT**2} - {mean[i]} * {mean[j]}) + {PRIOR} * p_v{i}_{j}) / (n + {PRIOR}) as v{i}_{j}" for i, j in _pairs()]
    centre = [f"(n * ({mean[i]}) + p_n * p_m{i}) / (n + p_n) as m{i}" for i in range(len(X))]
    g = g.selectExpr(*KEYS, *centre, *cov)
    for j in range(len(X)):  # one column of the factor at a time
        left = {i: f"v{i}_{j}" + (f" + {FLOORS[X[i]] ** 2!r}D" if i == j else "") + "".join(f" - c{i}_{k} * c{j}_{k}" for k in range(j)) for i in range(j, len(X))}
        root = f"sqrt(greatest({left[j]}, 1e-9D))"
        g = g.selectExpr("*", *(f"{root} as c{i}_{j}" if i == j else f"({left[i]}) / {root} as c{i}_{j}" for i in left))
    return g.selectExpr("*", "2 * (" + " + ".join(f"ln(c{i}_{i})" for i in range(len(X))) + ") as logdet")


def _distance(rows: DataFrame, model: DataFrame, groups: int) -> DataFrame:
    """Adds d2, the squared Mahalanobis distance, by forward substitution."""
    factor = model.selectExpr(*KEYS, *(f"m{i}" for i in range(len(X))), *(f"c{i}_{j}" for i, j in _pairs()))
    out = rows.join(maybe_broadcast(factor, groups, 100_000), KEYS)
    for i, x in enumerate(X):
        y = f"{x} / {UNIT}D - m{i}" + "".join(f" - c{i}_{k} * y{k}" for k in range(i))
        out = out.selectExpr("*", f"({y}) / c{i}_{i} as y{i}")
    return out.selectExpr(*rows.columns, " + ".join(f"y{i} * y{i}" for i in range(len(X))) + " as d2")


def _closest(rows: DataFrame, coverage: float, groups: int) -> DataFrame:
    """Rows of each group up to the distance that ``coverage`` of them do not exceed."""
    names = [c for c in rows.columns if c != "d2"]
    rows = rows.selectExpr(*names, "cast(floor(log2(1 + d2) * 64) as int) as bin")
    bins = rows.groupBy(*KEYS, "bin").agg(F.count("*").alias("n"))
    part = ", ".join(KEYS)
    bins = bins.selectExpr(*KEYS, "bin", f"sum(n) over (partition by {part} order by bin) - n as before", f"sum(n) over (partition by {part}) as every")
    cut = bins.where(f"before < every * {coverage!r}D").groupBy(*KEYS).agg(F.max("bin").alias("cut"))
    return rows.join(maybe_broadcast(cut, groups, 100_000), KEYS).where("bin <= cut").select(*names)


def _starts(rows: DataFrame, coverage: float, groups: int) -> DataFrame:
    """Rows that each start keeps: the closest to the medians, and two subsets of an eighth."""
    mid = rows.groupBy("grp").agg(*(F.expr(f"percentile(round({x} / 20) * 20, 0.5) as q{i}") for i, x in enumerate(X)))
    near = rows.join(maybe_broadcast(mid, groups, 100_000), "grp")
    d2 = " + ".join(f"power(({x} - q{i}) / {UNIT * 2 * FLOORS[x]!r}D, 2)" for i, x in enumerate(X))
    near = near.selectExpr(*rows.columns, "0 as start", f"{d2} as d2")
    eighth = f"cast(pmod(xxhash64(grp, {', '.join(X)}), 8) as int) as start"
    return _closest(near, coverage, groups).unionByName(rows.selectExpr("*", eighth).where("start in (1, 2)"))


def _best(models: DataFrame) -> DataFrame:
    """Of each group the model with the smallest determinant, as start 0; fall: how far it lies below start 0."""
    rest = [c for c in models.columns if c not in (*KEYS, "fall")]
    best = models.groupBy("grp").agg(F.min(F.struct("logdet", "start", *(c for c in rest if c != "logdet"))).alias("x"), F.max(F.when(F.col("start") == 0, F.col("logdet"))).alias("old"))
    return materialise(best.select("grp", F.lit(0).alias("start"), *(F.col(f"x.{c}").alias(c) for c in rest), (F.col("old") - F.col("x.logdet")).alias("fall")), "mcd-best")


def mcd_models(rows: DataFrame, prior: DataFrame, groups: int, coverage: float = 0.75) -> DataFrame:
    """Estimates of every group of rows(grp, statistics), as start 0; prior has the ``groups`` groups."""
    p, many = len(X), 3 * groups
    scale = coverage / chi2_cdf(chi2_quantile(coverage, p), p + 2)
    every = rows.withColumn("start", F.explode(F.array(*(F.lit(i) for i in range(3)))))
    kept = _starts(rows, coverage, many)
    for _ in range(FIRST_STEPS - 1):
        first = materialise(_estimate(kept, scale, prior, many), "mcd-start")
        kept = _closest(_distance(every, first, many), coverage, many)
    model, one = _best(_estimate(kept, scale, prior, many)), rows.withColumn("start", F.lit(0))
    for _ in range(MOST_STEPS):
        new = _estimate(_closest(_distance(one, model, groups), coverage, groups), scale, prior, groups)
        model = _best(model.drop("fall").unionByName(new.withColumn("start", F.lit(1))))
        fall = model.agg(F.max("fall")).first()[0]
        if fall is None or fall < FALL:
            break
    model = model.drop("fall")
    near = _distance(one, model, groups).where(F.col("d2") <= chi2_quantile(0.975, p)).drop("d2")
    final = _estimate(near, 0.975 / chi2_cdf(chi2_quantile(0.975, p), p + 2), prior, groups)
    # a group without rows near its centre keeps the model before
    both = final.withColumn("_o", F.lit(0)).unionByName(model.withColumn("_o", F.lit(1)))
    rest = [c for c in both.columns if c not in ("grp", "_o")]
    both = both.groupBy("grp").agg(F.min(F.struct("_o", *rest)).alias("x")).select("grp", *(F.col(f"x.{c}").alias(c) for c in rest))
    return materialise(both, "mcd-final")


def quality_verdicts(docs: DataFrame, coverage: float = 0.75, accept: float = 1 - 1e-7) -> DataFrame:
    """doc_id, the base counts, base_failed, d2 (null if failed) and kept of every row."""
    keep = ["doc_id", "_lang", "_source"]
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("lang").cast("string"), F.lit("\0")).alias("_lang"), F.coalesce(F.col("source").cast("string"), F.lit("\0")).alias("_source"), "text")
    counts = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    rows = materialise(base_counts(docs, keep), "quality-counts")
    good = rows.where(~F.col("base_failed")).select(*counts, F.to_json(F.array("_lang")).alias("lang"), F.to_json(F.array("_lang", "_source")).alias("grp"), *statistic_vector())
    vectors = materialise(good, "quality-vectors")
    groups = materialise(vectors.select("lang", "grp").distinct(), "quality-groups")
    wide = [F.lit((2 * FLOORS[X[i]]) ** 2 if i == j else 0.0).alias(f"p_v{i}_{j}") for i, j in _pairs()]
    prior = groups.select(F.col("lang").alias("grp")).distinct().select("grp", F.lit(0.0).alias("p_n"), *(F.lit(0.0).alias(f"p_m{i}") for i in range(len(X))), *wide)
    prior = materialise(prior, "quality-prior")
    langs = mcd_models(vectors.select(F.col("lang").alias("grp"), *X), prior, prior.count(), coverage)
    shape = [*(F.col(f"m{i}").alias(f"p_m{i}") for i in range(len(X))), *(F.col(f"v{i}_{j}").alias(f"p_v{i}_{j}") for i, j in _pairs())]
    prior = groups.join(langs.withColumnRenamed("grp", "lang"), "lang").select("grp", F.lit(float(PRIOR_CENTRE)).alias("p_n"), *shape)
    n = groups.count()
    models = mcd_models(vectors.select("grp", *X), materialise(prior, "quality-prior"), n, coverage)
    judged = _distance(vectors.withColumn("start", F.lit(0)), models.withColumn("start", F.lit(0)), n)
    judged = judged.select(*counts, "d2", (F.col("d2") <= chi2_quantile(accept, len(X))).alias("kept"))
    failed = rows.where("base_failed").select(*counts, F.lit(None).cast("double").alias("d2"), F.lit(False).alias("kept"))
    return judged.unionByName(failed)


def op4_robust_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts on all documents."""
    return quality_verdicts(table(spark, sf_dir, "documents"))


def keep_good(docs: DataFrame) -> DataFrame:
    """Documents whose verdict is to keep them; repeated rows of an id share the verdict of any kept one."""
    ids = materialise(quality_verdicts(docs).where("kept").select("doc_id").distinct(), "quality-kept")
    return docs.join(maybe_broadcast(ids, ids.count()), docs["doc_id"].eqNullSafe(ids["doc_id"]), "left_semi")
