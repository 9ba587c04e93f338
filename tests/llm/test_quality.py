import random
import re

import numpy as np
import pytest

from gradsift.llm import quality as Q


def brute(text):
    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams, cover = {}, set()
    for i in range(len(w) - 2):
        grams.setdefault(tuple(w[i : i + 3]), []).append(i)
    for at in grams.values():
        if len(at) > 1:
            cover.update(i + j for i in at for j in range(3))
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)


def rows(n=700):
    rnd = random.Random(1)
    out = []
    for i in range(n):
        words = ["".join(rnd.choice("abcdeé") for _ in range(rnd.randrange(2, 9))) for _ in range(rnd.choice([3, 60, 120, 300]))]
        if i % 50 == 7:
            words = [w + rnd.choice(["***", "%%%", "$$$"]) for w in words]
        text = "".join(w + rnd.choice([" ", " ", " ", "\n", "\t"]) for w in words)
        if i % 9 == 0:
            text = "same line\n" * rnd.randrange(4) + text + text[: rnd.randrange(len(text))]
        out.append((i, text, rnd.choice(["en", "de"]), rnd.choice(["s1", "s2", None])))
    return out + [(1000, None, None, None), (1001, "", "en", "s1"), (1002, " \n\n ", "en", "s1"), (1003, "a b a b a", "en", "s1"), (1004, "x " * 30000, "en", "s1"), (None, "a b", "en", "s1"), (1, out[1][1], out[1][2], out[1][3])]


def test_counts_and_verdicts(spark):
    data = rows()
    df = spark.createDataFrame([(*r, "x") for r in data], "doc_id long, text string, lang string, source string, kept string").repartition(3)
    got = Q.quality_verdicts(df).collect()
    want = sorted(((i, *brute(t)) for i, t, *_ in data), key=str)
    assert sorted(((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got), key=str) == want
    by = {r.doc_id: r for r in got}
    good = [r for r in got if not r.base_failed]
    assert {r.doc_id for r in good if not r.kept and r.doc_id % 9} == {r.doc_id for r in good if r.doc_id % 50 == 7 and r.doc_id % 9}
    assert not any(r.kept for r in good if r.doc_id % 50 == 7)
    assert not any(r.kept for r in got if r.base_failed) and by[1000].kept is False
    kept = Q.keep_good(df.repartition(5))
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in got if r.kept}


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string, lang string, source string")
    assert Q.quality_verdicts(df).count() == 0


def prior(spark, grps, wide=1.0, centre=0.0, n=0.0):
    cols = {f"p_m{i}": centre for i in range(5)} | {f"p_v{i}_{j}": wide if i == j else 0.0 for i, j in Q._pairs()}
    return spark.createDataFrame([(g, n, *cols.values()) for g in grps], "grp string, p_n double, " + ", ".join(f"{c} double" for c in cols))


def frame(spark, groups):
    return spark.createDataFrame([(g, *map(int, r)) for g, x in groups.items() for r in x], "grp string, " + ", ".join(f"{c} long" for c in Q.X))


def cloud(rnd, n):
    return np.round(rnd.normal([3, 5, 1, 1, 2], [1, 0.5, 0.7, 0.3, 1], (n, 5)) * Q.UNIT).astype(int)


def test_estimate_matches_numpy(spark):
    groups = {"g": cloud(np.random.default_rng(2), 300), "h": cloud(np.random.default_rng(3), 4)}
    df, floors = frame(spark, groups), np.diag(np.array(list(Q.FLOORS.values())) ** 2)
    model = Q._estimate(df.selectExpr("*", "0 as start"), 1.5, prior(spark, "gh", 2.0, 1.0, 5.0), 2)
    logdet = {r.grp: r.logdet for r in model.collect()}
    d2 = {g: sorted(r.d2 for r in Q._distance(df.selectExpr("*", "0 as start"), model, 2).where(f"grp = '{g}'").collect()) for g in groups}
    for g, x in groups.items():
        v, n = x / Q.UNIT, len(x)
        c = (n * 1.5 * np.cov(v.T, bias=True) + Q.PRIOR * 2 * np.eye(5)) / (n + Q.PRIOR) + floors
        z = v - (n * v.mean(0) + 5) / (n + 5)
        assert logdet[g] == pytest.approx(np.linalg.slogdet(c)[1]) and np.allclose(d2[g], np.sort(np.einsum("ij,jk,ik->i", z, np.linalg.inv(c), z)), rtol=1e-6)


def test_models_find_outliers_whatever_start_they_disturb(spark):
    rnd = np.random.default_rng(2)
    groups = {"far": cloud(rnd, 400), "few": cloud(rnd, 3), "one": cloud(rnd, 1), "same": np.tile(cloud(rnd, 1), (80, 1))}
    groups["far"][:40] += 20_000
    groups["few"][0] += 20_000
    df = frame(spark, groups)
    p = prior(spark, groups, 1.0, 2.0, 5.0)
    got = Q._distance(df.selectExpr("*", "0 as start"), Q.mcd_models(df, p, 4).selectExpr("* except (start)", "0 as start"), 4).collect()
    limit = Q.chi2_quantile(1 - 1e-7, 5)
    out = [(r.grp, r.x_length > 15_000) for r in got if r.d2 > limit]
    assert len(got) == 484 and sorted(out) == [("far", True)] * 40 + [("few", True)]


def test_chosen_start_has_the_smallest_determinant(spark):
    rnd = np.random.default_rng(5)
    df = frame(spark, {"g": np.concatenate([cloud(rnd, 300), cloud(rnd, 120) + 4000])})
    p, scale = prior(spark, "g"), 1.2
    starts = Q.materialise(Q._estimate(Q._starts(df, 0.75, 3), scale, p, 3), "starts")
    best = Q._best(starts).collect()
    assert len(best) == 1 and best[0].logdet == min(r.logdet for r in starts.collect()) and starts.count() == 3
    chain, model = [best[0].logdet], Q._best(starts)
    for _ in range(2):
        new = Q._estimate(Q._closest(Q._distance(df.selectExpr("*", "0 as start"), model, 1), 0.75, 1), scale, p, 1)
        model = Q._best(model.drop("fall").unionByName(new.selectExpr("* except (start)", "1 as start")))
        chain.append(model.first().logdet)
    assert all(a >= b for a, b in zip(chain, chain[1:], strict=False)) and chain[0] > chain[-1]


def test_chi2():
    assert Q.chi2_quantile(0.975, 5) == pytest.approx(12.8325, abs=1e-3) and Q.chi2_cdf(6.6257, 5) == pytest.approx(0.75, abs=1e-4)
