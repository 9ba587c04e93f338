"""Best-two-fit packing of tokenised documents into sequences of bounded length.

Only the lengths decide a packing, so the plan is made on the histogram of lengths, which has at
most ``capacity`` entries at any size of the input.  A bin is filled greedily with the longest
unpacked length that fits; if a gap remains, its shortest document is taken out and replaced by
the two unpacked documents that fit the widened gap most tightly, when they fill more of it.  The
same pattern is repeated while its lengths last, so the plan's size is bounded by the capacity
too (at most capacity/length patterns can exhaust a length).  Pieces then find their place
through their rank among pieces of equal length: ranks are counted within tasks and shifted by
sums over tasks, so no key, however frequent, is gathered in one place.

Defined results: null or empty text is one end token; equal rows are packed each; a null id keeps
its rows; further columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm.bpe import text_blocks, word_encoder
from gradsift.llm.common import materialise, table
from gradsift.llm.kernels import lean

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, local long"


def _encode(path: str, capacity: int, end_id: int):
    end = int(end_id).to_bytes(4, "little")

    def run(batches):
        encoder, task = word_encoder(path), TaskContext.get().partitionId()
        seen = [0] * (capacity + 1)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            ids = batch.column(0).to_pylist()
            cols: list[list] = [[] for _ in range(7)]
            for i, j in text_blocks(texts):
                for doc, got in zip(ids[i:j], encoder.encode(texts[i:j]), strict=True):
                    got += end
                    for piece, start in enumerate(range(0, len(got) // 4, capacity)):
                        part = got[4 * start : 4 * (start + capacity)]
                        n = len(part) // 4
                        for col, x in zip(cols, (doc, piece, start, n, zlib.crc32(part), task, seen[n]), strict=True):
                            col.append(x)
                        seen[n] += 1
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [x.split()[0] for x in PIECES.split(", ")])

    return run


def tightest_pair(lengths: np.ndarray, left: np.ndarray, gap: int, above: int) -> tuple[int, int] | None:
    """Two available lengths whose sum is the largest within the gap and above a bound.

    lengths: ascending, with ``left`` of each unpacked.
    """
    a = np.arange(len(lengths))
    b = np.minimum(np.searchsorted(lengths, gap - lengths, side="right") - 1, a)
    b = np.where((b == a) & (left < 2), b - 1, b)
    ok = b >= 0
    if not ok.any():
        return None
    total = np.where(ok, lengths + lengths[np.maximum(b, 0)], 0)
    best = int(total.argmax())
    if total[best] <= above or total[best] > gap:
        return None
    return int(lengths[best]), int(lengths[b[best]])


def best_two_fit(counts: dict[int, int], capacity: int) -> list[tuple[int, dict[int, int]]]:
    """(repeats, {length: number in the bin}) of every pattern, in the order of filling."""
    left = dict(counts)
    open_ = sorted(x for x, n in left.items() if n)
    plan = []
    while open_:
        used: dict[int, int] = {}
        rem, at = capacity, len(open_)
        while rem and (at := bisect_right(open_, rem, 0, at)):
            x = open_[at - 1]
            used[x] = min(rem // x, left[x])
            rem -= used[x] * x
            at -= 1
        if rem:
            small = min(used)
            gap = rem + small
            some = np.array([x for x in open_[: bisect_right(open_, gap)] if left[x] > used.get(x, 0)], np.int64)
            free = np.array([left[x] - used.get(x, 0) for x in some.tolist()], np.int64)
            if len(some) and (pair := tightest_pair(some, free, gap, small)):
                used[small] -= 1
                for x in pair:
                    used[x] = used.get(x, 0) + 1
                used = {x: n for x, n in used.items() if n}
        times = min(left[x] // n for x, n in used.items())
        plan.append((times, used))
        gone = False
        for x, n in used.items():
            left[x] -= n * times
            gone = gone or not left[x]
        if gone:
            open_ = [x for x in open_ if left[x]]
    return plan


def _placer(plan: list[tuple[int, dict[int, int]]], shift: int = 40):
    """Maps (length, rank among equal lengths) to (sequence, offset)."""
    base, taken, rows = 0, {}, []
    for times, used in plan:
        offset = 0
        for x, n in used.items():
            rows.append(((x << shift) + taken.get(x, 0), n, base, offset))
            taken[x] = taken.get(x, 0) + n * times
            offset += x * n
        base += times
    key, many, first, offset = (np.array(c, np.int64) for c in zip(*sorted(rows), strict=True)) if rows else (np.zeros(0, np.int64),) * 4

    def run(batches):
        for b in batches:
            n, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            want = (n << shift) + rank
            at = np.searchsorted(key, want, side="right") - 1
            i = want - key[at]
            out = b.select(["doc_id", "piece", "start", "length", "ids_crc32"])
            yield pa.RecordBatch.from_arrays(
                [*out.columns, pa.array(first[at] + i // many[at]), pa.array(offset[at] + i % many[at] * n)],
                [*out.schema.names, "sequence_id", "offset"],
            )

    return run


def pack_documents(docs: DataFrame, path: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """One row per piece: where it stands in its document and in its sequence."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    pieces = materialise(docs.mapInArrow(lean(_encode(path, capacity, end_id)), PIECES), "pack-pieces")
    counts = materialise(pieces.groupBy("task", "length").agg(F.count("*").alias("n")), "pack-counts")
    # at most ``capacity`` rows come to the driver
    plan = best_two_fit({r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}, capacity)
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    shifts = counts.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shift"))
    ranked = pieces.join(shifts.hint("merge"), ["task", "length"]).withColumn("rank", F.col("local") + F.col("shift"))
    return ranked.drop("task", "local", "shift").mapInArrow(
        _placer(plan), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    )


def sequence_ids(docs: DataFrame, packed: DataFrame, path: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """(sequence_id, ids): the token ids of every packed sequence (unique document ids needed)."""
    end = int(end_id).to_bytes(4, "little")

    def run(batches):
        encoder = word_encoder(path)
        for b in batches:
            doc, piece, ids = [], [], []
            for d, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                got = np.frombuffer(encoder.encode([t or ""])[0] + end, "<u4").astype(np.int64)
                for k, start in enumerate(range(0, len(got), capacity)):
                    doc.append(d)
                    piece.append(k)
                    ids.append(got[start : start + capacity])
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(ids, pa.list_(pa.int64()))], ["doc_id", "piece", "ids"])

    tokens = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, piece int, ids array<long>")
    rows = packed.select("doc_id", "piece", "sequence_id", "offset").join(tokens, ["doc_id", "piece"])
    rows = rows.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("x"))
    return rows.select("sequence_id", F.flatten(F.col("x.ids")).alias("ids"))


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_best_two_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 4096 tokens."""
    return pack_documents(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))
