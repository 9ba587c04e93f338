"""Queries on texts count all of a text, not its beginning."""

from collections import Counter

import pytest

from gradsift.workloads import cost_queries as C
from gradsift.workloads import relational_queries as Q
from gradsift.workloads import training_queries as TQ

LONG = "abcdef" * 30 + "Zwölf Größen 😀 am Ende"
TEXTS = [(1, LONG, "de"), (2, "ab", "en"), (3, None, "en"), (4, "x" * 5000, "fr"), (5, "one two three " * 40 + "Four", "en")]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("texts"))
    rows = [(i, t, lang, "s", len(t or "")) for i, t, lang in TEXTS]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{d}/documents.parquet")
    return d


def brute():
    code = lambda g: (ord(g[0]) * 961 + ord(g[1]) * 31 + ord(g[2])) * 7919 % 2147483647 % 16384
    return Counter((i, code(t.lower()[j : j + 3])) for i, t, _ in TEXTS if t for j in range(len(t) - 2))


def test_trigrams_of_whole_texts(spark, folder):
    want = brute()
    assert {(r.doc_id, r.coord): r.n for r in Q.char_trigrams(spark, folder).collect()} == want
    total = Counter()
    for (_, c), n in want.items():
        total[c] += n
    assert {r.coord: r.n for r in Q.ngram_counts(spark, folder).collect()} == total


def test_language_examples_of_whole_texts(spark, folder):
    want = Counter()
    for (i, c), n in brute().items():
        want[i, c % 256] += n
    got = {r.ex_id: {x.coord: x.val for x in r.x} for r in TQ.language_examples(spark, folder).collect()}
    assert set(got) == {1, 4, 5}
    for i, x in got.items():
        size = sum(n for (j, _), n in want.items() if j == i)
        assert x == pytest.approx({c: n / size * 10 for (j, c), n in want.items() if j == i})


def test_bleu_of_whole_texts(spark, tmp_path):
    start = "the same opening of both texts " * 8
    a, b = start + "and then one end of it", start + "and then another quite different end"
    spark.createDataFrame([(1, a, "en"), (2, b, "en"), (3, a, "de")], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.n: r for r in C.bleu_pairs(spark, str(tmp_path)).collect()}
    ref, cand = a.split(" "), b.split(" ")
    for n in range(1, 5):
        have, want = (Counter(tuple(s[i : i + n]) for i in range(len(s) - n + 1)) for s in (cand, ref))
        assert (got[n].total, got[n].matched) == (have.total(), (have & want).total())
    assert got[1].total == len(cand) and got[1].score < 100
