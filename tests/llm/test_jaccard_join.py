import itertools
import random
import re

import numpy as np
import pytest

from gradsift.llm import jaccard_join as J

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, k, percent):
    sets = []
    for i, text in rows:
        w = [x for x in WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))]
        sets.append({tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    root = {i: i for i, _ in rows}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for (a, x), (b, y) in itertools.combinations(zip([i for i, _ in rows], sets, strict=True), 2):
        if x and y and 100 * len(x & y) >= percent * len(x | y):
            p, q = find(a), find(b)
            root[max(p, q)] = min(p, q)
    return {(i, len(s), find(i)) for (i, _), s in zip(rows, sets, strict=True)}


def corpus(seed, n, vocab=400, edits=0.02):
    rnd = random.Random(seed)
    bases = [[f"w{rnd.randrange(vocab)}" for _ in range(rnd.choice([1, 2, 3, 5, 12, 40, 90]))] for _ in range(max(2, n // 8))]
    rows = []
    for i in range(n):
        w = list(rnd.choice(bases))
        for j in range(len(w)):
            if rnd.random() < edits:
                w[j] = f"x{rnd.randrange(50)}"
        rows.append((i * 3 + 1, " ".join(w).upper() if rnd.random() < 0.1 else "\t".join(w)))
    return rows


@pytest.mark.parametrize("k,percent,block", [(3, 90, 256), (5, 80, 256), (3, 90, 6), (2, 70, 5)])
def test_matches_brute_force(spark, k, percent, block):
    rows = corpus(k * percent + block, 220) + [(5000, None), (5001, ""), (5002, " \n ")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {tuple(r) for r in J.signature_tree_join(df, k, percent, block).select("doc_id", "n_shingles", "component_id").collect()}
    assert got == brute(rows, k, percent)


def test_tree_finds_every_component_pair():
    rnd = np.random.default_rng(3)
    base = [np.unique(rnd.integers(0, 2**63, 80, dtype=np.uint64)) for _ in range(12)]
    sets = [np.unique(np.r_[b[rnd.random(len(b)) > 0.03], rnd.integers(0, 2**63, 2, dtype=np.uint64)]) for b in base for _ in range(7)]
    got = J.tree_links(sets, 85)
    root = list(range(len(sets)))
    find = lambda x: x if root[x] == x else find(root[x])
    for a, b in got:
        assert J.linked(sets[a], sets[b], 85)
        root[find(a)] = find(b)
    for a, b in itertools.combinations(range(len(sets)), 2):
        if J.linked(sets[a], sets[b], 85):
            assert find(a) == find(b)


def test_links_between_two_trees():
    rnd = np.random.default_rng(4)
    base = [np.unique(rnd.integers(0, 2**63, rnd.integers(1, 90), dtype=np.uint64)) for _ in range(15)]
    copy = lambda b: np.unique(np.r_[b[rnd.random(len(b)) > 0.05], rnd.integers(0, 2**63, 2, dtype=np.uint64)])
    left, right = [copy(b) for b in base for _ in range(6)], [copy(b) for b in base[::3] for _ in range(3)]
    for x, y in ((left, right), (right, left), (left[:1], right)):
        got = J.tree_links(x, 80, y)
        every = [*x, *y]
        root = list(range(len(every)))
        find = lambda k: k if root[k] == k else find(root[k])  # noqa: E731, B023
        for a, b in got:
            assert a < len(x) <= b and J.linked(every[a], every[b], 80)
            root[find(a)] = find(b)
        assert all(find(a) == find(len(x) + b) for a, p in enumerate(x) for b, q in enumerate(y) if J.linked(p, q, 80))


def test_forest_spans_what_shares_keys():
    rnd = np.random.default_rng(5)
    key, node = rnd.integers(0, 60, 300).astype(np.uint64), rnd.integers(0, 120, 300)
    kept, u, v, n = J.forest(key, node)
    assert len(kept) == len(np.unique(key)) and len(u) == len(np.unique(u)) and (n > 0).all()
    root = {k: k for k in range(120)}
    find = lambda k: k if root[k] == k else find(root[k])
    for k in np.unique(key):
        some = node[key == k]
        for x in some:
            root[find(x)] = find(some[0])
    label = dict(zip(u.tolist(), v.tolist(), strict=True))
    assert all((label.get(a, a) == label.get(b, b)) == (find(a) == find(b)) for a in range(120) for b in range(120))


def test_no_set_that_links_is_left_out(spark):
    rows = corpus(77, 400, vocab=60)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for words, percent in ((3, 90), (5, 80), (2, 60)):
        _, able = J.can_link(df, words, percent, 1 << 20)
        able = {r.doc_id for r in able.collect()}
        linked = [(i, c) for i, n, c in brute(rows, words, percent) if n]
        sizes = {c: sum(c == x for _, x in linked) for _, c in linked}
        texts = {}
        for i, t in rows:
            texts.setdefault(" ".join(t.lower().split()), []).append(i)
        for same in texts.values():
            one = next((c for i, c in linked if i == same[0]), None)
            if one is not None and sizes[one] > len(same):
                assert able & set(same)


def test_edge_cases(spark):
    schema = "doc_id long, text string, cluster string, keys int, n_shingles double"
    assert J.signature_tree_join(spark.createDataFrame([], schema)).count() == 0
    rows = [(None, "a b c", "x", 1, 0.0), (2, "a b c", None, 1, 0.0), (2, "a b c", "x", 1, 0.0), (1, "a b c", "x", 1, 0.0)]
    df = spark.createDataFrame(rows, schema)
    got = sorted(map(tuple, J.signature_tree_join(df, 3, 90).collect()), key=str)
    assert got == sorted([(None, 1, None), (2, 1, 1), (2, 1, 1), (1, 1, 1)], key=str)
    kept = J.keep_first_of_component(df, 3, 90)
    assert kept.columns == df.columns and sorted((r.doc_id for r in kept.collect()), key=str) == [1, None]
    kept = J.keep_first_of_component(df.unionByName(df), 3, 90)
    assert sorted((r.doc_id for r in kept.collect()), key=str) == [1, None, None]


def test_very_long_word_and_text(spark):
    long = "z" * 300_000
    rows = [(1, long), (2, long), (3, "a " * 50_000)]
    got = {r.doc_id: r.component_id for r in J.signature_tree_join(spark.createDataFrame(rows, "doc_id long, text string"), 3, 90).collect()}
    assert got == {1: 1, 2: 1, 3: 3}
