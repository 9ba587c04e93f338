"""Document fingerprints as invertible Bloom lookup sketches of paragraph digests.

A text is cut at line feeds, and long lines behind words chosen by their hash, so that an insertion
moves no later cut.  Each paragraph's digest (with the count of its earlier equals) is added to
three cells of a small table: number, sum of digests, sum of check values.  Tables subtract cell by
cell, and peeling the cells that hold one digest recovers exactly the paragraphs in which two
versions differ.  If peeling gets stuck, both tables are built anew four times as large.  The
likeness of two texts is 1 - differing / all paragraphs; two empty texts have likeness 1.

Defined results: null text is empty; rows are ordered by id (null first) and, among equal ids, by
text, and the successor of the last row is the first; equal texts have equal fingerprints; further
columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import base64
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm import kernels as K
from gradsift.llm.bpe import text_blocks
from gradsift.llm.common import materialise, table

#: Cells of a fingerprint, and how much larger each retry is.
CELLS, LARGER = 24, 4
#: A line is cut behind about every eighth word.
CUT = 8
CELL = np.dtype([("n", "<i2"), ("digest", "<u8"), ("check", "<u4")])


def paragraphs(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(document number, digest) of every paragraph of every text, ascending by document."""
    data = np.frombuffer(b"".join(texts), np.uint8)
    offsets = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) for t in texts], out=offsets[1:])
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h, _, end = K.words(data, offsets, lower=False, ends=True)
    edge = np.zeros(len(data) + 1, bool)
    edge[offsets] = True
    edge[end[h % K.U(CUT) == 0]] = True
    edge[np.flatnonzero(data == 10) + 1] = True
    at = np.flatnonzero(edge)
    up, down = K.powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(K.BYTE_CODE[data] * up[:-1], out=total[1:])
    start, stop = at[:-1], at[1:]
    digest = K.mix((total[stop] - total[start]) * down[start] + (stop - start).astype(np.uint64))
    doc = np.searchsorted(offsets, start, side="right") - 1
    # equal paragraphs of one text are told apart by their number
    order = np.lexsort((digest, doc))
    same = np.zeros(len(order), bool)
    same[1:] = (doc[order][1:] == doc[order][:-1]) & (digest[order][1:] == digest[order][:-1])
    k = np.arange(len(order))
    nth = k - np.maximum.accumulate(np.where(same, 0, k))
    return doc[order], np.where(nth > 0, K.mix(digest[order] + nth.astype(np.uint64) * K.STEP[40]), digest[order])


def _check(digest: np.ndarray) -> np.ndarray:
    return K.mix(digest ^ K.STEP[41]) & K.U(0xFFFFFFFF)


def _cells(doc: np.ndarray, digest: np.ndarray, cells: int):
    third = cells // 3
    for j in range(3):
        yield doc * cells + j * third + (K.mix(digest + K.STEP[42 + j]) % K.U(third)).astype(np.int64)


class Tables:
    """One table of ``cells`` cells for each of ``n`` documents."""

    def __init__(self, n: int, cells: int):
        self.n, self.cells = n, cells
        self.count = np.zeros(n * cells, np.int64)
        self.digest, self.check = np.zeros(n * cells, np.uint64), np.zeros(n * cells, np.uint64)

    def add(self, doc: np.ndarray, digest: np.ndarray, sign: np.ndarray) -> None:
        s = sign.astype(np.int64).view(np.uint64)
        value, check = digest * s, _check(digest) * s
        for at in _cells(doc, digest, self.cells):
            np.add.at(self.count, at, sign)
            np.add.at(self.digest, at, value)
            np.add.at(self.check, at, check)

    def peel(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(document, digest, sign) of all that can be recovered, and which tables came out empty."""
        out = []
        while True:
            at = np.flatnonzero(np.abs(self.count) == 1)
            sign = self.count[at]
            digest = self.digest[at] * sign.view(np.uint64)
            ok = _check(digest) * sign.view(np.uint64) == self.check[at]
            doc, digest, sign = at[ok] // self.cells, digest[ok], sign[ok]
            if not len(doc):
                break
            one = np.unique(K.mix(doc.astype(np.uint64) * K.STEP[45]) + digest, return_index=True)[1]
            doc, digest, sign = doc[one], digest[one], sign[one]
            self.add(doc, digest, -sign)
            out.append((doc, digest, sign))
        empty = ~(self.count.astype(bool) | self.digest.astype(bool)).reshape(self.n, self.cells).any(1)
        found = tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64))
        return (*found, empty)


def differing(a, b, n: int, cells: int = CELLS) -> np.ndarray:
    """Number of paragraphs in which document i of a and of b differ, by subtracting and peeling."""
    size = np.bincount(a[0], minlength=n) - np.bincount(b[0], minlength=n)
    out, open_ = np.zeros(n, np.int64), np.ones(n, bool)
    while open_.any():
        # a table of fewer cells than the difference of the sizes cannot be peeled
        now = np.flatnonzero(open_ & (np.abs(size) < cells))
        place = np.full(n, -1)
        place[now] = np.arange(len(now))
        tables = Tables(len(now), cells)
        for (doc, digest), sign in ((a, 1), (b, -1)):
            mine = place[doc] >= 0
            tables.add(place[doc[mine]], digest[mine], np.full(int(mine.sum()), sign))
        doc, _, _, empty = tables.peel()
        found = np.bincount(doc, minlength=len(now))
        out[now[empty]] = found[empty]
        open_[now[empty]] = False
        cells *= LARGER
    return out


def fingerprint_strings(doc: np.ndarray, digest: np.ndarray, n: int) -> list[str]:
    tables = Tables(n, CELLS)
    tables.add(doc, digest, np.ones(len(doc), np.int64))
    cell = np.zeros(n * CELLS, CELL)
    cell["n"], cell["digest"], cell["check"] = tables.count, tables.digest, tables.check
    raw = cell.tobytes()
    step = CELLS * CELL.itemsize
    return [base64.b64encode(raw[i * step : (i + 1) * step]).decode() for i in range(n)]


def subtract(one: str, two: str) -> tuple[list[int], list[int], bool]:
    """Digests only in one, only in two, and whether all were recovered, from two fingerprints."""
    a, b = (np.frombuffer(base64.b64decode(x), CELL) for x in (one, two))
    t = Tables(1, CELLS)
    t.count = (a["n"] - b["n"]).astype(np.int64)
    t.digest = a["digest"] - b["digest"]
    t.check = (a["check"].astype(np.int64) - b["check"].astype(np.int64)).astype(np.int32).astype(np.int64).view(np.uint64)
    # sums of check values are kept modulo 2**32; compare them so
    low = K.U(0xFFFFFFFF)
    left, right = [], []
    while True:
        at = np.flatnonzero((np.abs(t.count) == 1) & True)
        sign = t.count[at]
        digest = t.digest[at] * sign.view(np.uint64)
        ok = (_check(digest) * sign.view(np.uint64)) & low == t.check[at] & low
        if not ok.any():
            break
        d, s = digest[ok][:1], sign[ok][:1]
        (left if s[0] > 0 else right).append(int(d[0]))
        t.add(np.zeros(1, np.int64), d, -s)
    return left, right, not (t.count.any() or t.digest.any())


def compare(texts: list[str], following: list[str]) -> dict[str, list]:
    """What the query returns of each text and its successor."""
    n = len(texts)
    quarter = [len(t) // 4 for t in texts]
    edited = [t[: len(t) - q] + x[:q] for t, q, x in zip(texts, quarter, following, strict=True)]
    raw = [e.encode() for e in edited]
    own, other, nxt = paragraphs([t.encode() for t in texts]), paragraphs(raw), paragraphs([x.encode() for x in following])

    def near(b):
        total = np.bincount(own[0], minlength=n) + np.bincount(b[0], minlength=n)
        return np.where(total > 0, 1 - differing(own, b, n) / np.maximum(total, 1), 1.0).tolist()

    return {
        "n_chars": [len(t) for t in texts],
        "edited_sha256": [sha256(r).hexdigest() for r in raw],
        "fingerprint": fingerprint_strings(*own, n),
        "edited_fingerprint": fingerprint_strings(*other, n),
        "near_edited": near(other),
        "near_next": near(nxt),
    }


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
OPEN = RESULT + ", part int, head struct<id:bigint,text:string>, tail struct<id:bigint,text:string>"
TYPES = {"n_chars": pa.int64(), "edited_sha256": pa.string(), "fingerprint": pa.string(), "edited_fingerprint": pa.string(), "near_edited": pa.float64(), "near_next": pa.float64()}
PAIR = pa.struct([("id", pa.int64()), ("text", pa.string())])


def _batch(ids: list, texts: list[str], part: int, head=None, tail=None, count: int | None = None) -> pa.RecordBatch:
    """Results of all but the last text, or a row that holds the ends of a partition."""
    n = len(ids) - 1 if count is None else count
    got = compare(texts[:n], texts[1 : n + 1]) if n else {c: [] for c in TYPES}
    cols = [pa.array(ids[:n], pa.int64()), *(pa.array(got[c], k) for c, k in TYPES.items())]
    cols += [pa.array([part] * n, pa.int32()), pa.array([None] * n, PAIR), pa.array([None] * n, PAIR)]
    if tail is not None:
        row = [pa.array([None], c.type) for c in cols]
        row[-3:] = pa.array([part], pa.int32()), pa.array([head], PAIR), pa.array([tail], PAIR)
        cols = row
    return pa.RecordBatch.from_arrays(cols, [x.strip().split()[0] for x in RESULT.split(",")] + ["part", "head", "tail"])


def _walk(batches):
    part, head, held_id, held = TaskContext.get().partitionId(), None, [], []
    for b in batches:
        ids, texts = held_id + b.column(0).to_pylist(), held + [t or "" for t in b.column(1).to_pylist()]
        if head is None and ids:
            head = {"id": ids[0], "text": texts[0]}
        for i, j in text_blocks(texts[:-1], 1 << 20):
            yield _batch(ids[i : j + 1], texts[i : j + 1], part)
        held_id, held = ids[-1:], texts[-1:]
    if held:
        yield _batch([], [], part, head, {"id": held_id[0], "text": held[0]}, 0)


def _ends(batches):
    for b in batches:
        ids, texts, nxt = b.column(0).to_pylist(), [t or "" for t in b.column(1).to_pylist()], [t or "" for t in b.column(2).to_pylist()]
        got = compare(texts, nxt)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *(pa.array(got[c], k) for c, k in TYPES.items())], [x.strip().split()[0] for x in RESULT.split(",")])


def fingerprint_chain(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited version, and their likeness.

    Rows are ranged by id, so a text and its successor meet in one task; only the two ends of each
    partition wait for a small second step.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ranged = docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    rows = materialise(ranged.mapInArrow(_walk, OPEN), "fingerprints")
    ends = rows.where("tail is not null").select("part", "head", "tail")
    order = Window.orderBy("part")  # one row per partition
    ends = ends.withColumn("following", F.coalesce(F.lead("head.text").over(order), F.first("head.text").over(order)))
    last = ends.select(F.col("tail.id").alias("doc_id"), F.col("tail.text").alias("text"), "following").mapInArrow(_ends, RESULT)
    return rows.where("tail is null").drop("part", "head", "tail").unionByName(last)


def op9_invertible_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, each against its edited text and its successor."""
    return fingerprint_chain(table(spark, sf_dir, "documents"))
