import hashlib
import random

import numpy as np
import pytest

from gradsift.llm import suffix_dedup as S


def brute(rows, length):
    least = {}
    for i, t in rows:
        b = (t or "").encode()
        if i is not None:
            for s in range(len(b) - length + 1):
                k = b[s : s + length]
                least[k] = min(least.get(k, i), i)
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for s in range(len(b) - length + 1):
            if i is not None and least[b[s : s + length]] < i:
                gone[s : s + length] = b"\1" * length
        spans = sum(1 for j in range(len(b)) if gone[j] and (j == 0 or not gone[j - 1]))
        out.append((i, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()))
    return sorted(out, key=str)


def corpus(seed, n=120):
    rnd = random.Random(seed)
    words = ["the ", "of ", "ñandú ", "aa", "b", "\n", "xyz ", "🙂"]
    make = lambda k: "".join(rnd.choice(words) if rnd.random() < 0.5 else rnd.choice("abcdefgh ") for _ in range(k))
    common = [make(rnd.randrange(5, 60)) for _ in range(8)]
    rows = []
    for i in range(n):
        kind = rnd.random()
        if kind < 0.25 and rows:
            t = rnd.choice(rows)[1] or ""
            if rnd.random() < 0.6 and t:
                p = rnd.randrange(len(t))
                t = t[:p] + rnd.choice("QZ") + t[p + 1 :]
        else:
            t = "".join(rnd.choice(common) if rnd.random() < 0.4 else make(rnd.randrange(30)) for _ in range(rnd.randrange(6)))
        rows.append((rnd.randrange(10**9), t))
    return rows


@pytest.mark.parametrize("seed,length,q", [(1, 50, 16), (2, 50, 16), (3, 20, 8), (4, 17, 16)])
def test_matches_brute_force(spark, seed, length, q):
    rows = corpus(seed) + [(5, None), (6, ""), (None, "zz" * 80), (7, "zz" * 80), (8, "zz" * 81), (9, "a" * 400), (10, "a" * 49), (10**15, "b" * 3000), (10**15 + 1, "b" * 3000)]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, runs string").repartition(3)
    got = S.suffix_dedup(df, length, q).collect()
    assert sorted(map(tuple, got), key=str) == brute(rows, length)


def test_suffix_order_of_wide_symbols():
    """Products of symbols beyond 63 bits are ranked first."""
    rnd = np.random.default_rng(1)
    for n in (3, 40, 501):
        few = rnd.integers(1 << 40, 1 << 41, 5)
        t = few[rnd.integers(0, 5, n)]
        assert S.suffix_order(t).tolist() == sorted(range(n), key=lambda i: t[i:].tolist())


def test_a_frequent_anchor_is_spread(spark):
    """One q-gram with many different contexts: groups of equal halves are small, and nothing is lost."""
    rnd = random.Random(4)
    gram = "0000000000000001"
    word = lambda n: "".join(rnd.choice("abcdefghijklmnop") for _ in range(n))
    halves = [word(34) for _ in range(6)]
    rows = [(i, rnd.choice(halves + [word(34)] * 3) + gram + rnd.choice(halves + [word(34)] * 3)) for i in range(150)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(map(tuple, S.suffix_dedup(df, 50, 16).collect()), key=str) == brute(rows, 50)


def test_suffix_order():
    rnd = np.random.default_rng(5)
    for n in [0, 1, 2, 3, 4, 5, 6, 7, 8, 30, 31, 32, 200]:
        for top in (1, 2, 5, 200):
            t = rnd.integers(1, top + 1, n)
            assert S.suffix_order(t).tolist() == sorted(range(n), key=lambda i: t[i:].tolist())


def test_rows_of_one_id_with_different_texts(spark):
    """Each row is cut by its own runs and none by a row of the same id."""
    rnd = random.Random(6)
    p, x, y = ("".join(rnd.choice("abcdef ") for _ in range(122)) for _ in range(3))
    rows = [(1, p), (5, p), (5, x), (5, x + p), (5, x), (7, y), (7, "ab" + y + x), (7, None), (7, p[:49] + y), (9, y)]
    got = S.suffix_dedup(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert sorted(map(tuple, got), key=str) == brute(rows, 50)
    rows = [(i, t, "r", 0, "e") for i, t in rows]
    out = S.cut_repeats(spark.createDataFrame(rows, "doc_id long, text string, runs string, tag long, bucket string"))
    assert out.columns == ["doc_id", "text", "runs", "tag", "bucket"] and {tuple(r)[2:] for r in out.collect()} == {("r", 0, "e")}
    assert sorted(len(r.text) for r in out.where("doc_id = 5").collect()) == [122, 122, 122]


def test_cut_and_edges(spark):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    p = "The quick brown fox jumps over the lazy dog and then é some more words."
    rows = [(1, p + " one", "en", "s", 3), (2, "two " + p, "en", "s", 4), (3, p, None, None, None), (4, None, "en", "s", None), (2, "two " + p, "en", "s", 4)]
    out = S.cut_repeats(spark.createDataFrame(rows, schema))
    got = sorted((r.doc_id, r.text, r.n_chars) for r in out.collect() if r.text is not None)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"] and [g[0] for g in got] == [1, 2, 2]
    assert got[0] == (1, p + " one", len(p) + 4) and got[1][1] == "two "[: len(got[1][1])]
    assert S.suffix_dedup(spark.createDataFrame([], schema)).count() == 0
    assert S.cut_repeats(spark.createDataFrame([], schema)).count() == 0


def test_grams_that_meet_by_chance_bring_no_text_along():
    """One q-gram in all texts, but other bytes beside it in each: nothing is left to review but what shares a half as well."""
    import pyarrow as pa

    rnd = random.Random(5)
    make = lambda n: "".join(rnd.choice("abcdefghijklmnop") for _ in range(n))
    gram = max((make(16) for _ in range(3000)), key=lambda g: int(S.K.rolling(np.frombuffer(g.encode(), np.uint8), 16)[0]))  # an anchor nearly everywhere

    def reviewed(texts):
        b = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts), pa.array([0] * len(texts), pa.int64())], ["doc_id", "text", "tag"])
        t = pa.Table.from_batches(S._sample(50, 16, 1)(iter([b])))
        named = S._name(1)(t)
        return [x for k, x in zip(named.column("kind").to_pylist(), named.column("blob").to_pylist(), strict=True) if k == S.REVIEW]

    apart = [make(60) + gram + make(60) for _ in range(300)]
    assert not reviewed(apart)
    tail = make(25)
    found = reviewed([*apart, make(60) + gram + tail + make(40), make(60) + gram + tail + make(40)])
    doc, _, at, _, sides = S._read_places(found, 3)
    assert set(doc.tolist()) == {300, 301} and set(sides[at <= 60].tolist()) <= {2}
