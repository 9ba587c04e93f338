import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from gradsift.llm import fingerprints as FP
from gradsift.llm import token_rollup as TR
from gradsift.llm import warc
from gradsift.llm.packing import tokenizer_path

SHA = lambda s: hashlib.sha256(s.encode()).hexdigest()


def texts(n=90):
    rnd = random.Random(8)
    word = lambda: "".join(rnd.choice("abcdefgé") for _ in range(rnd.randrange(1, 7)))
    return ["".join(word() + rnd.choice("   \n") for _ in range(rnd.choice([0, 1, 5, 60, 500]))) for _ in range(n)] + [None, "", "same\nsame\nsame\n", "x" * 200_000]


def test_chain_against_brute_force(spark):
    rows = [(i * 7 + 1, t) for i, t in enumerate(texts())]
    random.Random(1).shuffle(rows)
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, part int").repartition(5)
    got = {r.doc_id: r for r in FP.fingerprint_chain(df).collect()}
    rows = sorted((i, t or "") for i, t in rows)
    assert len(got) == len(rows)
    sets = [Counter(FP.paragraphs([t.encode()])[1].tolist()) for _, t in rows]
    for k, (i, t) in enumerate(rows):
        nxt = rows[(k + 1) % len(rows)][1]
        q = len(t) // 4
        edited = t[: len(t) - q] + nxt[:q]
        e = Counter(FP.paragraphs([edited.encode()])[1].tolist())
        like = lambda a, b: 1 - (sum((a - b).values()) + sum((b - a).values())) / (sum(a.values()) + sum(b.values())) if a or b else 1.0
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(t), SHA(edited))
        assert r.near_edited == pytest.approx(like(sets[k], e)) and r.near_next == pytest.approx(like(sets[k], sets[(k + 1) % len(rows)]))
    assert len({r.fingerprint for r in got.values()}) == len({t for _, t in rows})
    assert FP.fingerprint_chain(df.limit(0)).count() == 0


def test_subtract_recovers_digests():
    a = ["one two three\nfour five\nsix\n", "one two three\nfour 5\nsix\nseven\n"]
    parts = [set(FP.paragraphs([x.encode()])[1].tolist()) for x in a]
    one, two = (FP.fingerprint_strings(*FP.paragraphs([x.encode()]), 1)[0] for x in a)
    left, right, whole = FP.subtract(one, two)
    assert whole and set(left) == parts[0] - parts[1] and set(right) == parts[1] - parts[0]
    assert FP.subtract(one, one) == ([], [], True)
    many = FP.fingerprint_strings(*FP.paragraphs(["\n".join(map(str, range(500))).encode()]), 1)[0]
    assert not FP.subtract(one, many)[2]


def test_paragraphs_are_stable_under_insertion():
    rnd = random.Random(3)
    w = [f"w{rnd.randrange(999)}" for _ in range(400)]
    a, b = " ".join(w).encode(), " ".join(w[:100] + ["new"] + w[100:]).encode()
    x, y = (set(FP.paragraphs([t])[1].tolist()) for t in (a, b))
    assert len(x ^ y) <= 6 and len(x) > 20


def pages():
    rnd = random.Random(2)
    fake = "WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:77>\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    big = "<p>é " * 400
    rows = [(i, f"http://x/{i}", rnd.choice(["", "short", fake, fake * 30, big, big + "1", "\r\n\r\n", f"u{i} " * 500])) for i in range(150)]
    return rows + [(500, None, None), (501, "a b\r\nX: y", "\x00z"), (502, "u", "y" * 3_000_000), (7, *rows[7][1:]), (None, "n", "q")]


def test_archives(spark, tmp_path):
    rows = pages()
    df = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, size string").repartition(3)
    warc.write_archives(df, f"{tmp_path}/w", file_bytes=200_000)
    got = warc.read_archives(spark, f"{tmp_path}/w", with_payload=True).collect()
    groups = {}
    for i, _, h in rows:
        if len((h or "").encode()) >= 1000:
            groups[h] = max(groups.get(h, i), i)
    want = []
    for i, _, h in rows:
        b = (h or "").encode()
        keep = groups.get(h, i)
        want.append((i, len(b), hashlib.sha1(b).hexdigest(), "response" if keep == i else "revisit", None if keep == i else keep))
    assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got), key=str) == sorted(want, key=str)
    by = {i: h or "" for i, _, h in rows}
    assert all(bytes(r.payload).decode() == by[r.page_id] for r in got if r.record_type == "response")
    warc.write_archives(df.limit(0), f"{tmp_path}/e")
    assert warc.read_archives(spark, f"{tmp_path}/e").count() == 0


def test_pointer_jumping():
    at = np.array([0, 5, 9, 20, 33])
    assert warc.reachable(at, np.array([9, 20, 33, 33, 50])).tolist() == [True, False, True, False, True]
    assert warc.reachable(at[1:], np.array([9, 20, 33, 50])).tolist() == [False] * 4
    n = 1000
    assert warc.reachable(np.arange(n), np.arange(n) + 1).all() and warc.reachable(np.zeros(0, int), np.zeros(0, int)).tolist() == []


def test_ledger(spark, tmp_path):
    rows = [("a", "en", "v1", 5, 4), ("a", "en", "v1", 7, 7), ("b", None, "v1", 2, 9), (None, "de", "v1", None, 3), ("a", "en", "v2", 1, 1)]
    df = spark.createDataFrame(rows, "source string, lang string, version string, n_tokens long, old_tokens long")
    ledger = TR.TokenLedger(spark, f"file://{tmp_path}/ledger")
    assert ledger.totals().count() == 0
    old = df.withColumn("n_tokens", df.old_tokens)
    assert ledger.commit("b1", TR.inserted(old)) and not ledger.commit("b1", TR.inserted(old))
    assert ledger.commit("b2", TR.revised(df)) and ledger.commit("b3", TR.deleted(df.where("source = 'b' or version = 'v2'")))
    assert ledger.commit("b4", TR.inserted(df.limit(0)))
    df.limit(1).write.parquet(f"{tmp_path}/ledger/data/b9-orphan")
    want = {("a", "en", "v1", 2, 12), (None, "de", "v1", 1, 0)}
    assert {tuple(r) for r in ledger.totals().collect()} == want
    assert {tuple(r) for r in TR.TokenLedger(spark, f"file://{tmp_path}/ledger").totals().collect()} == want


def test_ledger_survives_a_dead_writer(spark, tmp_path):
    df = spark.createDataFrame([("a", "en", "v1", 5)], "source string, lang string, version string, n_tokens long")
    ledger = TR.TokenLedger(spark, f"file://{tmp_path}/ledger")
    (tmp_path / "ledger" / "commits").mkdir(parents=True)
    (tmp_path / "ledger" / "commits" / "b1").touch()  # a marker whose content never came
    assert not ledger.committed("b1") and ledger.totals().count() == 0
    assert ledger.commit("b1", TR.inserted(df)) and not ledger.commit("b1", TR.inserted(df))
    data = ledger.batches()["b1"]
    assert not ledger._mark("b1", "data/other") and ledger.batches() == {"b1": data}  # a second writer loses
    assert [tuple(r) for r in ledger.totals().collect()] == [("a", "en", "v1", 1, 5)]


def test_whole_rollup_query_against_brute_force(spark, tmp_path):
    tokenizers = pytest.importorskip("tokenizers")
    rows = [(i, t, None if i % 7 == 0 else "de", f"s{i % 3}") for i, t in enumerate(texts(40))] + [(None, "no id, İ.", "de", "s1"), (3, "again", "de", "s0")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    want = Counter()
    for version in ("word_bpe_49k", "byte_bpe_50k"):
        library = tokenizers.Tokenizer.from_file(tokenizer_path(f"{version}.json"))
        for _, t, lang, source in rows:
            want[source, lang, version, "docs"] += 1
            want[source, lang, version, "tokens"] += len(library.encode(t or "", add_special_tokens=False).ids)
    got = {}
    for r in TR.op6_delta_rollup(spark, str(tmp_path)).collect():
        got[r.source, r.lang, r.version, "docs"], got[r.source, r.lang, r.version, "tokens"] = r.n_docs, r.n_tokens
    assert got == dict(want)


def test_token_counts(spark):
    tokenizers = pytest.importorskip("tokenizers")
    names = {"word_bpe_49k": tokenizer_path("word_bpe_49k.json"), "byte_bpe_50k": tokenizer_path("byte_bpe_50k.json")}
    rows = [(i, "s", "en", t) for i, t in enumerate(texts(20))]
    df = spark.createDataFrame(rows, "doc_id long, source string, lang string, text string")
    got = {(r.doc_id, r.version): r.n_tokens for r in TR.token_counts(df, *names.values()).collect()}
    for v, p in names.items():
        library = tokenizers.Tokenizer.from_file(p)
        assert all(got[i, v] == len(library.encode(t or "", add_special_tokens=False).ids) for i, _, _, t in rows)


def test_rollup_deletes_and_restores(spark, tmp_path, monkeypatch):
    rows = [(i, "a" if i % 2 else "b", "en", "v1", 10 + i, i) for i in range(9)]
    counts = spark.createDataFrame(rows, "doc_id long, source string, lang string, version string, n_tokens long, old_tokens long")
    monkeypatch.setattr(TR, "table", lambda spark, d, name: counts)
    monkeypatch.setattr(TR, "token_counts", lambda docs, *paths: docs)
    monkeypatch.setattr(TR, "materialise", lambda df, name: df)
    monkeypatch.setattr(TR, "tokenizer_path", lambda name: name)
    monkeypatch.setattr(TR, "fresh_path", lambda spark, name: f"file://{tmp_path}/ledger")
    sent = []
    commit = TR.TokenLedger.commit
    monkeypatch.setattr(TR.TokenLedger, "commit", lambda self, batch, df: sent.append((batch, commit(self, batch, df))))
    got = {tuple(r) for r in TR.op6_delta_rollup(spark, "").collect()}
    assert got == {("a", "en", "v1", 4, 10 * 4 + 1 + 3 + 5 + 7), ("b", "en", "v1", 5, 10 * 5 + 2 + 4 + 6 + 8)}
    assert [b for b, new in sent if new] == ["estimates", "exact", "removed", "restored"] and len(sent) == 8
    ledger = TR.TokenLedger(spark, f"file://{tmp_path}/ledger")
    gone = spark.read.parquet(f"{ledger.root}/{ledger.batches()['removed']}")
    assert {(r.source, r.n_docs, r.n_tokens) for r in gone.collect()} == {("a", -1, -13), ("b", -2, -26)}
