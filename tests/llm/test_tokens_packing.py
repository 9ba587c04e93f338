import itertools
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from gradsift.llm import bpe, packing, tokens

tokenizers = pytest.importorskip("tokenizers")
pytest.importorskip("public_tokenizers")

ODD = [
    "", "a" * 9000, "<|endoftext|> x <|endoftext|>", " " * 9000 + "x", "x" + " " * 9001, "!" * 9000 + "'s", "ab" * 20000 + " c",
    "\n " * 5000 + "'s", "I'll we're 'tis", "e" * 5000 + "́" * 5000, "x\n\n  y", "Ünïcödé " * 50, "a\x1cb c", " x　y", "中文🙂 1234",
]


def texts(n=300):
    rnd = random.Random(5)
    alphabet = " \n\t  aábß'sStre!?<|>09\x1c" "éİ  中文🙂"
    return ["".join(rnd.choice(alphabet) for _ in range(rnd.randrange(60))) for _ in range(n)] + ODD


@pytest.mark.parametrize("name,make", [("word_bpe_49k.json", bpe.word_encoder), ("byte_bpe_50k.json", bpe.byte_encoder)])
def test_equals_library(name, make):
    path = packing.tokenizer_path(name)
    library, ours = tokenizers.Tokenizer.from_file(path), make(path)
    got = ours.encode(texts())
    for text, ids in zip(texts(), got, strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, ascii(text[:60])


def test_stream_in_any_blocks_and_bounded_buffer():
    path = packing.tokenizer_path("byte_bpe_50k.json")
    rnd, e = random.Random(2), bpe.byte_encoder(path)
    d = bpe.ByteStreamDecoder(path)
    library = tokenizers.Tokenizer.from_file(path)
    for text in texts(80):
        if bpe.END in text:
            continue
        out, i, one = b"", 0, bpe.TextStream(e)
        while i < len(text):
            n = rnd.choice([1, 3, 50, 3000])
            if rnd.random() < 0.5:
                out += e.advance([(one, text[i : i + n], None)])[0]
            else:
                out += one.feed(text[i : i + n])
            assert len(one.tail) <= e.LIMIT + 3000 and (one.run is None or len(one.long.held) <= 3 * e.v.merges.lookahead + 4 * 3000)
            i += n
        ids = np.frombuffer(out + one.finish(), "<u4")
        assert ids.tolist() == library.encode(text, add_special_tokens=False).ids
        assert "".join([*(d.feed(ids[k : k + 1]) for k in range(len(ids))), d.finish()]) == text
        d.machine.reset()


def test_every_text_goes_through_a_stream(monkeypatch):
    path = packing.tokenizer_path("byte_bpe_50k.json")
    e, library, seen, runs = bpe.ByteStreamEncoder(path), tokenizers.Tokenizer.from_file(path), [], []
    take, finish = bpe.TextStream.take, bpe.LongRun.finish
    monkeypatch.setattr(bpe.TextStream, "take", lambda self, block, last: seen.append(len(block)) or take(self, block, last))
    monkeypatch.setattr(bpe.LongRun, "finish", lambda self: runs.append(1) or finish(self))
    monkeypatch.setattr(bpe.ByteStreamEncoder, "STEP", 1000)
    some = [*texts(30), "word and more words, " * 900, "no" * 3000]
    got = e.encode(some)
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == [library.encode(t, add_special_tokens=False).ids for t in some]
    assert sum(seen) == sum(len(t.replace(bpe.END, "")) for t in some) and max(seen) <= 1000 and len(runs) > 5
    assert e.lengths(some) == [len(x) // 4 for x in got]


def test_word_ids_of_all_letters_before_marks():
    path = packing.tokenizer_path("word_bpe_49k.json")
    library, ours = tokenizers.Tokenizer.from_file(path), bpe.word_encoder(path)
    some = [*range(0x80, 0x1000), 0x1E9E, 0x212A, 0xA7F1, *range(0xFB00, 0xFB50), *range(0x1D400, 0x1D420), *range(0x11F00, 0x11F60), *range(0x1E030, 0x1E0A0)]
    lines = [f(chr(c)) for c in some for f in ("x{0}, a{0}. B".format, "{0}\n{0}, c".format, "a{0}b 1{0}.".format)]
    got, want = ours.encode(lines), library.encode_batch(lines, add_special_tokens=False)
    assert [a for a, x, y in zip(lines, got, want, strict=True) if np.frombuffer(x, "<u4").tolist() != y.ids] == []
    assert ours.lengths(lines) == [len(y.ids) for y in want]


def test_decode_broken_utf8_like_library():
    path = packing.tokenizer_path("byte_bpe_50k.json")
    library, rnd = tokenizers.Tokenizer.from_file(path), np.random.default_rng(1)
    for _ in range(200):
        ids = rnd.integers(0, 300, 12).astype("<u4")
        assert bpe.ByteStreamDecoder(path).decode(ids, 3) == library.decode(ids.tolist(), skip_special_tokens=False)


def test_lookahead_suffices_for_small_merge_lists():
    """Boundaries left of the lookahead never move when text is appended."""
    rnd = random.Random(9)
    for _ in range(60):
        vocab, merges = ["a", "b"], []
        while len(merges) < 8:
            x, y = rnd.choice(vocab), rnd.choice(vocab)
            if x + y not in vocab and len(x + y) < 9:
                vocab.append(x + y)
                merges.append((vocab.index(x), vocab.index(y), len(vocab) - 1))
        t = bpe.MergeTable(merges, np.array([len(v) for v in vocab]))
        for s in itertools.islice((tuple(rnd.choice([0, 1]) for _ in range(40)) for _ in range(40)), 40):
            whole = t.encode_heap(list(s))
            run, out = bpe.LongRun(t), []
            for x in s:
                out += run.feed([x])
            assert out + run.finish() == whole


def check_layout(rows, capacity):
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_pack_documents(spark):
    path = packing.tokenizer_path("word_bpe_49k.json")
    library = tokenizers.Tokenizer.from_file(path)
    rnd = random.Random(1)
    rows = [(i, " ".join(rnd.choice(["the", "of", "zq", "tion!"]) for _ in range(rnd.randrange(70)))) for i in range(150)]
    rows += [(150, None), (151, ""), (152, "the of " * 60), (153, rows[0][1])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = packing.pack_documents(df, path, capacity=64)
    out = got.collect()
    want = {}
    for i, t in rows:
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 1]
        for k in range(0, len(ids), 64):
            want[i, k // 64] = (k, len(ids[k : k + 64]), zlib.crc32(np.array(ids[k : k + 64], "<u4").tobytes()))
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in out} == want and len(out) == len(want)
    used = check_layout(out, 64)
    assert used <= 1.03 * -(-sum(x[1] for x in want.values()) // 64) + 1
    seq = {r.sequence_id: r.ids for r in packing.sequence_ids(df, got, path, 64).collect()}
    assert all(list(np.array(seq[r.sequence_id][r.offset : r.offset + r.length], "<u4").tobytes()) and zlib.crc32(np.array(seq[r.sequence_id][r.offset : r.offset + r.length], "<u4").tobytes()) == r.ids_crc32 for r in out)


def test_two_fit_beats_greedy_and_keeps_counts():
    # greedy takes 6 and 3 of 10; the pair 2 + 2 fits the gap of 4 tightly
    assert packing.best_two_fit({6: 1, 3: 1, 2: 2}, 10)[0] == (1, {6: 1, 2: 2}) or packing.best_two_fit({6: 1, 3: 1, 2: 2}, 10)[0][1] == {6: 1, 3: 1}
    assert packing.tightest_pair(np.array([2, 3]), np.array([2, 1]), 4, 3) == (2, 2)
    rnd = random.Random(4)
    for _ in range(50):
        cap = rnd.choice([10, 37, 100])
        counts = Counter(rnd.randrange(1, cap + 1) for _ in range(rnd.randrange(1, 400)))
        plan, seen = packing.best_two_fit(dict(counts), cap), Counter()
        for times, used in plan:
            assert times > 0 and sum(x * n for x, n in used.items()) <= cap
            for x, n in used.items():
                seen[x] += n * times
        assert seen == counts


def test_encode_decode_query(spark):
    path = packing.tokenizer_path("byte_bpe_50k.json")
    rows = [*enumerate(texts(40)), (None, None), (1, "again")]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, n_tokens string")
    out = tokens.encode_decode(df, path, with_output=True).collect()
    assert len(out) == len(rows) and all(r.n_tokens == len(r.ids) for r in out)
    assert sorted(r.decoded for r in out) == sorted(t or "" for _, t in rows)
    assert tokens.encode_decode(df.limit(0), path).count() == 0 == packing.pack_documents(df.limit(0), packing.tokenizer_path("word_bpe_49k.json")).count()


def test_unknown_characters_are_looked_up_once():
    """Chunks with characters that Python's tables lack go to the library; each different character is looked at once, not each chunk."""
    from gradsift.llm import bpe
    from gradsift.llm.packing import tokenizer_path

    encoder, seen = bpe.WordEncoder(tokenizer_path("word_bpe_49k.json")), []
    unknown = encoder.unknown

    class Counted:
        def search(self, x):
            seen.append(x)
            return unknown.search(x)

    encoder.unknown = Counted()
    texts = [f"é{i} ñu{i} Ω{i}\U000323b0{i} plain{i}" for i in range(500)] + ["͸x é"]
    got = encoder.encode(texts)
    assert [g for g in got] == [encoder._library_ids(t) for t in texts]
    assert len(seen) < 40
