import random
import zlib

import numpy as np
import pytest

import corpus_pipeline
from gradsift.llm import quality, registry
from gradsift.llm.packing import tokenizer_path


def test_names():
    assert [n.split("_")[0] for n in registry.QUERIES] == [f"op{i}" for i in range(1, 11)]
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "repeated_passages", "packing"]


def brute(rows, kept):
    """Stages two to four on the rows that the quality rules keep, all pairs and all windows."""
    from test_jaccard_join import brute as near

    rows = sorted((i, t) for i, t in rows if i in kept)
    first = {c for _, _, c in near(rows, 5, 80)}
    rows = [(i, t) for i, t in rows if i in first]
    seen, out = {}, {}
    for i, t in rows:
        b = t.encode()
        for s in range(len(b) - 49):
            seen.setdefault(b[s : s + 50], i)
    for i, t in rows:
        b = t.encode()
        gone = bytearray(len(b))
        for s in range(len(b) - 49):
            if seen[b[s : s + 50]] < i:
                gone[s : s + 50] = b"\1" * 50
        rest = bytes(x for x, g in zip(b, gone) if not g).decode("utf-8", "ignore")
        if rest.strip() or not any(gone):
            out[i] = rest
    return out


def test_run_against_brute_force(spark, tmp_path):
    tokenizers = pytest.importorskip("tokenizers")
    library = tokenizers.Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    rnd = random.Random(6)
    word = lambda: "".join(rnd.choice("abcdefghé") for _ in range(rnd.randrange(2, 9)))
    base = [" ".join(word() for _ in range(rnd.choice([60, 90, 150]))) for _ in range(60)]
    passage = " ".join(word() for _ in range(30))
    texts = base + [base[0], base[1] + " extra", base[2][:200] + " " + base[3], "too short", base[4] + " " + passage, base[5] + " " + passage, " ".join("x**%" for _ in range(80))]
    rows = [(i * 2 + 1, t, "en", "s", len(t)) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    kept = {r.doc_id for r in quality.quality_verdicts(docs).where("kept").collect()}
    assert len(kept) >= 60 and rows[63][0] not in kept
    want = {}
    for i, t in brute([(r[0], r[1]) for r in rows], kept).items():
        ids = [*library.encode(t, add_special_tokens=False).ids, 1]
        want[i] = (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r.doc_id: (r.length, r.ids_crc32) for r in got} == want
