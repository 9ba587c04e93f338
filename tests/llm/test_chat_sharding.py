import hashlib
import random
import zlib
from itertools import product

import pytest
from pyspark.sql import functions as F

from gradsift.llm import chat, sharding

SHA = lambda s: hashlib.sha256(s.encode()).hexdigest()


def chats():
    rnd = random.Random(3)
    bits = [chat.START, chat.STOP, "<\\|im_end|>", "<\\\\|im_start|>", "\n", "<", "|>", "ok", "é🙂", "\\", "%", "", "assistant"]
    rows = [(c, t, rnd.choice(["user", "assistant", "system"]), "".join(rnd.choice(bits) for _ in range(rnd.randrange(6)))) for c in range(120) for t in range(rnd.randrange(1, 5))]
    return rows + [(900, 0, None, None), (901, 0, "a\nb%0A<|im_end|>", "x"), (902, 1, "user", "t"), (902, 1, "assistant", "s"), (902, 1, "assistant", "s"), (903, None, "assistant", "q" * 100_000), (None, 1, "user", "n")]


def test_round_trip(spark):
    rows = chats()
    df = spark.createDataFrame([(*r, "x") for r in rows], "conv_id long, turn long, role string, text string, span string").repartition(3)
    out = {r.conv_id: r for r in chat.format_chats(df).withColumn("loss", chat.masked_text(F.col("formatted"), F.col("loss_spans"))).collect()}
    want = {}
    for c, t, r, x in rows:
        want.setdefault(c, []).append((-1 if t is None else t, r or "", x or ""))
    assert out.keys() == want.keys()
    for c, turns in want.items():
        turns = [(r, x) for _, r, x in sorted(turns)]
        assert [(t.role, t.text) for t in out[c].turns] == turns
        assert out[c].loss == "".join(x for r, x in turns if r == "assistant")
        assert out[c].formatted.count(chat.START) == out[c].formatted.count(chat.STOP) == len(turns)
    assert chat.format_chats(df.limit(0)).count() == 0
    clean = [x for x in rows if x[0] == 902]
    assert out[902].formatted == "".join(f"<|im_start|>{r}\n{x}<|im_end|>\n" for _, _, r, x in sorted(clean))


def test_hilbert_is_a_continuous_curve(spark):
    for n, bits in ((2, 3), (3, 2), (3, 4)):
        pts = list(product(range(1 << bits), repeat=n))
        df = spark.createDataFrame(pts, ", ".join(f"c{i} int" for i in range(n)))
        got = df.select(sharding.hilbert_index([F.col(f"c{i}") for i in range(n)], bits).alias("h"), *df.columns).collect()
        path = [tuple(r)[1:] for r in sorted(got)]
        assert sorted(r.h for r in got) == list(range(len(pts)))
        assert all(sum(abs(a - b) for a, b in zip(p, q, strict=True)) == 1 for p, q in zip(path, path[1:], strict=False))


@pytest.mark.parametrize("n,part", [(0, 256), (5, 256), (500, 7)])
def test_shards(spark, n, part):
    rnd = random.Random(n)
    rows = [(i, rnd.choice(["a", "b c", None, "é" * rnd.randrange(3000)]), rnd.choice(["en", "de", None]), "src0" if rnd.random() < 0.5 else f"src{rnd.randrange(9)}", "x") for i in range(n)]
    rows += rows[:3]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, shard string")
    got = sharding.hilbert_shards(df, 24, part=part).collect()
    assert sorted((r.doc_id, r.size, r.text_crc32) for r in got) == sorted((i, 8 + len((t or "").encode()), zlib.crc32((t or "").encode())) for i, t, *_ in rows)
    by = {s: sorted(r.slot for r in got if r.shard == s) for s in range(24)}
    assert all(v == list(range(len(v))) for v in by.values()) and {r.shard for r in got} <= set(range(24))
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    order = sorted((r.shard, r.curve) for r in got)
    assert [c for _, c in order] == sorted(c for _, c in order)


def test_places_follow_the_order_of_values(spark):
    rows = [(v,) for v, n in {"a": 500, "b": 10, "c": 90, "d": 200, "e": 200}.items() for _ in range(n)] + [(None,)]
    df = spark.createDataFrame(rows, "v string").repartition(4)
    first = sharding.first_values(df, F.col("v"), 2)
    assert first == [(3, "e"), (2, "b")]
    got = dict(df.select("v", sharding.place_of(F.col("v"), first)).distinct().collect())
    assert [got[v] for v in "abcde"] == [0, 2, 2, 2, 3] and got[None] == 0


def test_files_are_skipped_by_every_dimension(spark):
    rnd = random.Random(11)
    rows = [(i, "x" * int(2 ** rnd.uniform(3, 13)), rnd.choice(["de", "en", "es", "fr"]), "s00" if rnd.random() < 0.33 else f"s{rnd.randrange(1, 20):02}") for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").repartition(4)
    stats = sharding.shard_statistics(df, sharding.hilbert_shards(df, 24)).collect()
    assert len(stats) == 24
    read = lambda c, v: sum(r[f"min_{c}"] <= v <= r[f"max_{c}"] for r in stats) / 24
    mean = {"lang": [read("lang", v) for v in ("de", "en", "es", "fr")], "source": [read("source", v) for v in sorted({r[3] for r in rows})], "size": [read("size", 8 + int(2**e)) for e in range(3, 13)]}
    mean = {c: sum(v) / len(v) for c, v in mean.items()}
    assert all(v < 0.6 for v in mean.values()) and sum(mean.values()) < 1.65, mean
