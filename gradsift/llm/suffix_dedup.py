"""Removal of repeated passages by distributed suffix sorting over a difference cover.

Every byte covered by a string of ``length`` bytes that also starts in a document with a smaller
id is removed.  Sorting all suffixes of the corpus would move many times its size, so the suffixes
are first dealt to buckets and reduced without loss:

1. Sample.  In every window of ``length`` bytes the q-gram with the smallest hash is an anchor.
   Equal windows choose equal anchors, so occurrences of one string always meet at one anchor.
2. Names.  All anchors are dealt by the hash of their q-gram.  An anchor's context is all bytes of
   the windows that can have chosen it.  Among equal contexts only the smallest document stays; the
   others are covered whole.  An anchor carries short hashes of the half on its left and on its right;
   a side whose q-gram and half no other document has is done, so q-grams that meet by chance, which
   grow with the square of the corpus, bring no text along.
3. Suffix order.  A window holds its anchor's q-gram and, on one side of it, at least half of its other
   bytes.  So a context is cut into a left and a right part, each dealt by the q-gram and the half
   next to it: windows that are equal meet, and a frequent q-gram is spread over many tasks.  Parts
   that meet are sorted as suffixes by the difference cover modulo 3: the sampled triples are sorted
   and named, names are sorted by recursion, the remaining suffixes are merged in, and adjacent
   prefixes are compared; a class of equal prefixes covers all members but those of its smallest
   document.

Tasks exchange packed columns, and buckets are as many as the bytes need; equal contexts are merged
before they are dealt.  Different contexts that share a q-gram and the half beside it meet in one task.

Defined results: null text is empty; rows without id are neither sources nor cut; rows with one id
are one document for the comparison, so they do not cut each other, but each is cut by its own
runs: ids with different texts carry a tag, a 64-bit hash of the text, beside the id.  Texts shorter
than ``length`` keep everything; further columns of any name are ignored or, by ``cut_repeats``, passed
on; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import pickle
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.llm import kernels as K
from gradsift.llm.common import discard, materialise, maybe_broadcast, table

LENGTH, GRAM = 50, 16
#: Bytes of text for each bucket of anchors or documents.
BUCKET_BYTES = 8 << 20
#: Symbols of the small groups that are put together for one suffix sort; a group is never divided.
SORT_SYMBOLS = 400_000
#: Runs of removed bytes that may be broadcast to the last pass.
BROADCAST_BYTES = 32 << 20
ANCHOR, COVER, REVIEW, SPAN = 0, 1, 2, 3
ROW = "bucket int, kind int, blob binary"


# packed columns ---------------------------------------------------------------


def _thin(a: np.ndarray, width: int) -> bytes:
    """Columns of bytes, least first, compressed: high bytes are nearly all equal."""
    return zlib.compress(np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes(), 1)


def _wide(data: bytes, width: int) -> np.ndarray:
    raw = np.frombuffer(zlib.decompress(data), np.uint8).reshape(width, -1)
    out = np.zeros((raw.shape[1], 8), np.uint8)
    out[:, :width] = raw.T
    return out.view("<u8").ravel()


def _cut(a: np.ndarray, width: int) -> bytes:
    return a.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def _grow(data: bytes, width: int) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8).reshape(-1, width)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :width] = raw
    return out.view("<u8").ravel()


def _steps(a: np.ndarray) -> np.ndarray:
    """Differences, wrapped to unsigned."""
    return np.diff(a.astype(np.int64), prepend=np.int64(0)).view(np.uint64)


def _places(doc: np.ndarray, tag: np.ndarray, *more: np.ndarray) -> bytes:
    """Documents, tags and non-negative places under 2**32, sorted by document; tags are mostly all zero."""
    return pickle.dumps([_thin(_steps(doc), 8), _thin(tag, 8) if tag.any() else b"", *(_thin(m, 4) for m in more)], 5)


def _read_places(blobs: list[bytes], n: int) -> tuple[np.ndarray, ...]:
    parts = [[np.zeros(0, np.int64)] for _ in range(n + 2)]
    for b in blobs:
        doc, tag, *more = pickle.loads(b)
        parts[0].append(np.cumsum(_wide(doc, 8).view(np.int64)))
        parts[1].append(_wide(tag, 8).view(np.int64) if tag else np.zeros(len(parts[0][-1]), np.int64))
        for p, m in zip(parts[2:], more, strict=True):
            p.append(_wide(m, 4).astype(np.int64))
    return tuple(np.concatenate(p) for p in parts)


def _deal(key: np.ndarray, n: int):
    """(bucket, indices) of each bucket that has any, order kept inside."""
    b = (key % K.U(n)).astype(np.int64)
    order = np.argsort(b, kind="stable")
    for part in np.split(order, np.flatnonzero(np.diff(b[order])) + 1) if len(order) else []:
        yield int(b[part[0]]), part


def _doc_key(doc: np.ndarray) -> np.ndarray:
    return K.mix(doc.view(np.uint64) + K.STEP[20])


def _rows(found) -> pa.RecordBatch:
    b, k, x = zip(*found, strict=True) if found else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(k, pa.int32()), pa.array(x, pa.binary())], ["bucket", "kind", "blob"])


# 1. sample --------------------------------------------------------------------


def _sliding(a: np.ndarray, w: int, f) -> np.ndarray:
    """f over each w adjacent values, by doubling."""
    size, cur = 1, a
    while size * 2 <= w:
        cur = f(cur[:-size], cur[size:])
        size *= 2
    return cur if size == w else f(cur[: len(a) - w + 1], cur[w - size :])


def anchors(data: np.ndarray, offsets: np.ndarray, length: int, q: int):
    """(document number, place, q-gram hash, context hash, hashes of the halves on the left and on the right) of every anchor.

    The hash of a half has 24 bits; 0 stands for a side that holds no window.
    """
    w = length - q + 1
    half = w // 2
    if len(data) < length:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.uint64, np.uint64, np.uint64, np.uint64))
    h = K.rolling(data, q)
    low = _sliding(h, w, np.minimum)
    last = np.repeat(offsets[1:], np.diff(offsets))
    low[np.arange(len(low)) + length > last[: len(low)]] = 0
    none = np.zeros(w - 1, np.uint64)
    best = _sliding(np.concatenate([none, low, none]), w, np.maximum)
    at = np.flatnonzero((best == h) & (h != 0))
    doc = np.searchsorted(offsets, at, side="right") - 1
    start, end = np.maximum(offsets[doc], at - w + 1), np.minimum(offsets[doc + 1], at + length)
    up, down = K.powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(K.BYTE_CODE[data] * up[:-1], out=total[1:])
    context = (total[end] - total[start]) * down[start]
    context = K.mix(context + (at - start).astype(np.uint64) * K.STEP[21] + (end - at).astype(np.uint64) * K.STEP[22])
    sides = []
    for side in (0, 1):
        first, last, begin = part_of(side, start, end, at, length, q)
        ok = np.flatnonzero(_usable(first, last, begin, start, end, length, half))
        code = np.zeros(len(at), np.uint64)
        b = begin[ok]
        code[ok] = np.maximum(K.mix((total[b + half] - total[b]) * down[b] + h[at[ok]]) >> K.U(40), K.U(1))
        sides.append(code)
    return doc, at - offsets[doc], h[at], context, *sides


def part_of(side: int, start, end, at, length: int, q: int):
    """(first, last) of the left or right part of contexts, and where the half beside the anchor begins."""
    w = length - q + 1
    half = w // 2
    if side == 0:
        return start, np.minimum(end, at + q + w - 1 - half), at - half
    return np.maximum(start, at - half), end, at + q


def _usable(first, last, begin, start, end, length: int, half: int) -> np.ndarray:
    """Whether a part holds a window and the whole half."""
    return (begin >= start) & (begin + half <= end) & (last - first >= length)


def _sample(length: int, q: int, buckets: int):
    def run(batches):
        for batch in batches:
            data, offsets = K.raw(batch.column(1))
            ids, tags = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 2))
            for first, last in K.pieces(offsets, BUCKET_BYTES):
                yield deal(data, offsets, ids, tags, first, last)

    def deal(data, offsets, ids, tags, first, last) -> pa.RecordBatch:
        parts = []
        for i, j in K.pieces(offsets[first : last + 1], 1 << 19):
            i, j = i + first, j + first
            lo, hi = offsets[i], offsets[j]
            doc, at, h, c, *halves = anchors(data[lo:hi], offsets[i : j + 1] - lo, length, q)
            parts.append((ids[doc + i], tags[doc + i], at, h, c, *halves))
        doc, tag, at, h, c, left, right = (np.concatenate(x) for x in zip(*parts, strict=True))
        # equal contexts of this batch: the smallest document speaks for all
        order = np.lexsort((doc, K.mix(h * K.STEP[23] + c)))
        same = np.zeros(len(order), bool)
        same[1:] = (h[order][1:] == h[order][:-1]) & (c[order][1:] == c[order][:-1])
        head = order[np.maximum.accumulate(np.where(same, 0, np.arange(len(order))))] if len(order) else order
        covered = order[doc[order] > doc[head]]
        keep = np.ones(len(doc), bool)
        keep[covered] = False
        found = []
        if len(covered):
            covered = covered[np.argsort(doc[covered], kind="stable")]
            for b, part in _deal(_doc_key(doc[covered]), buckets):
                part = covered[part]
                found.append((b, COVER, _places(doc[part], tag[part], at[part])))
        doc, tag, at, h, c, left, right = doc[keep], tag[keep], at[keep], h[keep], c[keep], left[keep], right[keep]
        for b, part in _deal(h, buckets):
            cols = [_cut(h[part] >> K.U(24), 5), _cut(c[part] >> K.U(8), 7), _places(doc[part], tag[part], at[part]), _cut(left[part], 3), _cut(right[part], 3)]
            found.append((b, ANCHOR, pickle.dumps(cols, 5)))
        return _rows(found)

    return run


# 2. names ---------------------------------------------------------------------


def met(group: np.ndarray, code: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Which anchors share q-gram and half (0: none) with one of another document."""
    order = np.lexsort((code, group))
    g, x, d = group[order], code[order], doc[order]
    fresh = np.ones(len(order), bool)
    fresh[1:] = (g[1:] != g[:-1]) | (x[1:] != x[:-1])
    first = np.flatnonzero(fresh)
    out = np.zeros(len(order), bool)
    if len(first):
        several = np.minimum.reduceat(d, first) < np.maximum.reduceat(d, first)
        out[order] = several[np.cumsum(fresh) - 1] & (x != 0)
    return out


def _name(buckets: int):
    def run(t: pa.Table) -> pa.Table:
        kind = t.column("kind").to_numpy()
        blobs = t.column("blob").to_pylist()
        found = [(b, COVER, x) for b, k, x in zip(t.column("bucket").to_pylist(), kind, blobs, strict=True) if k == COVER]
        mine = [pickle.loads(x) for x, k in zip(blobs, kind, strict=True) if k == ANCHOR]
        if mine:
            h = np.concatenate([_grow(x[0], 5) for x in mine])
            c = np.concatenate([_grow(x[1], 7) for x in mine])
            doc, tag, at = _read_places([x[2] for x in mine], 1)
            left, right = (np.concatenate([_grow(x[i], 3) for x in mine]) for i in (3, 4))
            order = np.lexsort((doc, c, h))
            h, c, doc, tag, at, left, right = h[order], c[order], doc[order], tag[order], at[order], left[order], right[order]
            new_h = np.ones(len(h), bool)
            new_h[1:] = h[1:] != h[:-1]
            new_c = new_h.copy()
            new_c[1:] |= c[1:] != c[:-1]
            head = np.maximum.accumulate(np.where(new_c, np.arange(len(h)), 0))
            covered = doc > doc[head]
            group = np.cumsum(new_h) - 1
            first = np.flatnonzero(new_h)
            contexts = np.add.reduceat(new_c, first, dtype=np.int64)
            several = np.minimum.reduceat(doc, first) < np.maximum.reduceat(doc, first)
            open_ = np.flatnonzero(~covered & ((contexts > 1) & several)[group])
            sides = np.zeros(len(h), np.int64)
            for bit, code in ((1, left), (2, right)):
                sides[open_] |= bit * met(group[open_], code[open_], doc[open_])
            for what, pick, more in ((COVER, covered, ()), (REVIEW, sides > 0, (h & K.U(0xFFFFFFFF), sides))):
                i = np.flatnonzero(pick)
                i = i[np.argsort(doc[i], kind="stable")]
                for b, part in _deal(_doc_key(doc[i]), buckets):
                    part = i[part]
                    found.append((b, what, _places(doc[part], tag[part], at[part], *(m[part] for m in more))))
        return pa.Table.from_batches([_rows(found)])

    return run


# 3. suffix order --------------------------------------------------------------


def _half_codes(data: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n bytes from each place, some places at a time."""
    up, out = K.powers(n)[0], np.empty(len(at), np.uint64)
    for i in range(0, len(at), 1 << 14):
        own = data[at[i : i + (1 << 14), None] + np.arange(n)]
        out[i : i + (1 << 14)] = (K.BYTE_CODE[own] * up).sum(1, dtype=np.uint64)
    return out


def _fetch(length: int, q: int, buckets: int):
    """Left and right parts of the contexts left, read from their documents and dealt by anchor and half."""
    w = length - q + 1
    half = w // 2

    def run(texts: pa.Table, marks: pa.Table) -> pa.Table:
        doc, tag, at, h, sides = _read_places(marks.column("blob").to_pylist(), 3)
        ids, tags = texts.column("doc_id").to_numpy(), texts.column("tag").to_numpy()
        found = []
        if len(doc) and len(ids):
            data, offsets = K.raw(texts.column("text"))
            have, want = _joint(ids, tags, doc, tag)
            order = np.argsort(have, kind="stable")
            row = np.minimum(np.searchsorted(have[order], want), len(ids) - 1)
            ok = have[order][row] == want
            doc, tag, at, h, sides, row = doc[ok], tag[ok], at[ok], h[ok], sides[ok], order[row[ok]]
            start, end = np.maximum(0, at - w + 1), np.minimum(np.diff(offsets)[row], at + length)
            for side in (0, 1):
                first, last, begin = part_of(side, start, end, at, length, q)
                ok = np.flatnonzero(_usable(first, last, begin, start, end, length, half) & (sides >> side & 1 > 0))
                if not len(ok):
                    continue
                place, first, last, begin = offsets[row[ok]], first[ok], last[ok], begin[ok]
                key = K.mix(K.mix(_half_codes(data, place + begin, half)) + (2 * h[ok] + side).astype(np.uint64) * K.STEP[24])
                for b, part in _deal(key, buckets):
                    size = (last - first)[part]
                    idx = np.repeat((place + first)[part] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
                    blob = [_thin(key[part] >> K.U(32), 4), zlib.compress(data[idx].tobytes(), 1), _thin(size, 2), _places(doc[ok[part]], tag[ok[part]], first[part])]
                    found.append((b, REVIEW, pickle.dumps(blob, 5)))
        return pa.Table.from_batches([_rows(found)])

    return run


def _joint(ids: np.ndarray, tags: np.ndarray, doc: np.ndarray, tag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One key for each (id, tag) on both sides; the id itself where no tag is set."""
    if not (tags.any() or tag.any()):
        return ids, doc
    one = np.unique(np.r_[ids, doc], return_inverse=True)[1]
    names, two = np.unique(np.r_[tags, tag], return_inverse=True)
    key = one * np.int64(len(names)) + two
    return key[: len(ids)], key[len(ids) :]


def _codes(*parts: tuple[np.ndarray, int]) -> list[np.ndarray]:
    """Order-preserving 63-bit codes of tuples; parts: columns of arrays with the bound of their values.

    Each part is a list of arrays that share one coding; values are combined left to right, and
    renamed by rank before a product would pass 63 bits.
    """
    columns, bound = parts[0]
    cut = np.cumsum([len(c) for c in columns])[:-1]
    code = np.concatenate(columns).astype(np.int64)
    for columns, more in parts[1:]:
        if bound * more >= 1 << 62:
            names, code = np.unique(code, return_inverse=True)
            bound = len(names)
        code = code * more + np.concatenate(columns)
        bound *= more
    return np.split(code, cut)


def suffix_order(t: np.ndarray) -> np.ndarray:
    """Suffix array of positive integers by the difference cover {1, 2} modulo 3."""
    n = len(t)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: t[i:].tolist()), np.int64)
    s = np.concatenate([t.astype(np.int64), np.zeros(3, np.int64)])
    top = int(s.max()) + 1
    one, two = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([one, two])
    # sort the sampled triples and name them
    (key,) = _codes(([s[sample]], top), ([s[sample + 1]], top), ([s[sample + 2]], top))
    order = np.argsort(key, kind="stable")
    fresh = np.ones(len(order), bool)
    fresh[1:] = key[order][1:] != key[order][:-1]
    name = np.empty(len(order), np.int64)
    name[order] = np.cumsum(fresh)
    if not fresh.all():
        order = suffix_order(name)  # recursion on the names, residue 1 before residue 2
        name[order] = np.arange(1, len(order) + 1)
    rank = np.zeros(n + 3, np.int64)
    rank[sample] = name
    sampled = sample[order]
    sampled = sampled[sampled < n]
    # the remaining suffixes follow from their first symbol and the rank behind it
    wide = n + 4
    rest = np.arange(0, n, 3)
    rest = rest[np.argsort(s[rest] * wide + rank[rest + 1], kind="stable")]
    j1, j2 = sampled[sampled % 3 == 1], sampled[sampled % 3 == 2]
    pair = lambda i: s[i] * wide + rank[i + 1]
    left, right = _codes(([s[j2], s[rest]], top), ([s[j2 + 1], s[rest + 1]], top), ([rank[j2 + 2], rank[rest + 2]], wide))
    place = np.arange(len(rest)) + np.searchsorted(pair(j1), pair(rest)) + np.searchsorted(left, right)
    out = np.full(n, -1, np.int64)
    out[place] = rest
    out[out < 0] = sampled
    return out


def covered_windows(contexts: list[tuple[np.ndarray, np.ndarray]], length: int):
    """Starts of windows, in the joined contexts, that also start in a smaller document.

    contexts: pieces (bytes joined, sizes) with ``doc`` of each context in the third place.
    """
    data, size, doc = contexts
    first = np.cumsum(size) - size
    gap = np.arange(len(size))
    joined = np.zeros(len(data) + len(size), np.int64)  # a zero ends each context
    owner = np.repeat(gap, size)
    joined[np.arange(len(data)) + owner] = data.astype(np.int64) + 1
    order = suffix_order(joined + 1)
    own = np.repeat(gap, size + 1)
    begin = first + gap
    ok = order + length <= (begin + size)[own[order]]
    starts = order[ok]
    if not len(starts):
        return starts, own
    window = np.lib.stride_tricks.sliding_window_view(joined.astype(np.uint16), length)
    fresh = np.ones(len(starts), bool)
    for i in range(1, len(starts), 1 << 16):  # compare adjacent prefixes
        a = starts[i - 1 : i - 1 + (1 << 16)]
        b = starts[i : i + (1 << 16)]
        fresh[i : i + len(b)] = (window[a[: len(b)]] != window[b]).any(1)
    at = np.flatnonzero(fresh)
    least = np.minimum.reduceat(doc[own[starts]], at)
    return starts[doc[own[starts]] > least[np.cumsum(fresh) - 1]], own


def _order(length: int, q: int, buckets: int):
    def run(t: pa.Table) -> pa.Table:
        parts = [pickle.loads(x) for x in t.column("blob").to_pylist()]
        h = np.concatenate([_wide(p[0], 4) for p in parts])
        size = np.concatenate([_wide(p[2], 2) for p in parts]).astype(np.int64)
        data = np.frombuffer(b"".join(zlib.decompress(p[1]) for p in parts), np.uint8)
        doc, tag, start = _read_places([p[3] for p in parts], 1)
        first = np.cumsum(size) - size
        _, inverse, count = np.unique(h, return_inverse=True, return_counts=True)
        by = np.flatnonzero(count[inverse] > 1)  # a part that meets no other shares no window
        by = by[np.argsort(h[by], kind="stable")]
        cut = [0]  # whole groups, as many as one sort takes
        edge = np.r_[np.flatnonzero(np.diff(h[by])) + 1, len(by)] if len(by) else []
        run_size = np.cumsum(size[by] + 1) if len(by) else []
        spans, last, done = [], 0, 0
        for e in edge:
            if run_size[e - 1] - done > SORT_SYMBOLS and last > cut[-1]:
                cut.append(last)
                done = run_size[last - 1]
            last = int(e)
        cut.append(last)
        for a, b in zip(cut, cut[1:], strict=False):
            group = by[a:b]
            if not len(group):
                continue
            n = size[group]
            idx = np.repeat(first[group] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            hit, own = covered_windows((data[idx], n, doc[group]), length)
            if len(hit):
                k = own[hit]
                begin = np.cumsum(n) - n + np.arange(len(n))
                spans.append((doc[group][k], tag[group][k], start[group][k] + hit - begin[k]))
        found = []
        if spans:
            d, g, s = (np.concatenate(x) for x in zip(*spans, strict=True))
            d, g, s, e = merged(d, g, s, s + length)
            for b, part in _deal(_doc_key(d), buckets):
                found.append((b, SPAN, _places(d[part], g[part], s[part], e[part])))
        return pa.Table.from_batches([_rows(found)])

    return run


def merged(doc: np.ndarray, tag: np.ndarray, start: np.ndarray, end: np.ndarray):
    """Maximal runs per document and tag; runs that touch are one."""
    order = np.lexsort((start, tag, doc))
    doc, tag, start, end = doc[order], tag[order], start[order], end[order]
    if not len(doc):
        return doc, tag, start, end
    shift = np.cumsum(np.r_[False, (doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1])]) * np.int64(1 << 33)
    reach = np.maximum.accumulate(end + shift)
    fresh = np.r_[True, (start + shift)[1:] > reach[:-1]]
    first = np.flatnonzero(fresh)
    return doc[first], tag[first], start[first], np.maximum.reduceat(end + shift, first) - shift[first]


# result -----------------------------------------------------------------------


def _runs(length: int, q: int):
    w = length - q + 1

    def run(t: pa.Table) -> pa.Table:
        kind = t.column("kind").to_numpy()
        blobs = t.column("blob").to_pylist()
        doc, tag, at = _read_places([x for x, k in zip(blobs, kind, strict=True) if k == COVER], 1)
        d2, g2, s2, e2 = _read_places([x for x, k in zip(blobs, kind, strict=True) if k == SPAN], 2)
        doc, tag, start, end = merged(np.r_[doc, d2], np.r_[tag, g2], np.r_[np.maximum(0, at - w + 1), s2], np.r_[at + length, e2])
        edge = np.r_[0, np.flatnonzero((doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1])) + 1] if len(doc) else np.zeros(0, np.int64)
        pairs = np.stack([start, end], 1).astype("<i4")
        blobs = [x.tobytes() for x in np.split(pairs, edge[1:])] if len(doc) else []
        return pa.table({"doc_id": pa.array(doc[edge], pa.int64()), "tag": pa.array(tag[edge], pa.int64()), "runs": pa.array(blobs, pa.binary())})

    return run


def repeated_runs(docs: DataFrame, length: int = LENGTH, q: int = GRAM) -> DataFrame:
    """(doc_id, tag, runs) of documents with removed bytes; runs: int32 pairs, the last may pass the end.

    tag is 0, but for ids with different texts ``_tag`` of the text that the runs belong to.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    docs = docs.where("doc_id is not null")
    ids = docs.groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("n"), (F.min(_tag("text")) < F.max(_tag("text"))).alias("differ"))
    total, differ = ids.agg(F.sum("n"), F.count_if("differ")).first()
    total = total or 0
    docs = docs.withColumn("tag", F.lit(0).cast("long"))
    if differ:
        twins = ids.where("differ").select("doc_id", F.lit(True).alias("twin"))
        docs = docs.join(maybe_broadcast(twins, differ), "doc_id", "left")
        docs = docs.select("doc_id", "text", F.when(F.col("twin"), _tag("text")).otherwise(F.lit(0)).alias("tag"))
    buckets = max(12, -(-total // BUCKET_BYTES))
    sample = docs.mapInArrow(K.lean(_sample(length, q, buckets)), ROW)
    named = materialise(sample.groupBy("bucket").applyInArrow(K.lean_group(_name(buckets)), ROW), "suffix-names")
    review = named.where(F.col("kind") == REVIEW)

    def owners(batches):
        for b in batches:
            doc = _read_places(b.column(0).to_pylist(), 3)[0]
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(doc))], ["doc_id"])

    wanted = materialise(review.select("blob").mapInArrow(owners, "doc_id long").distinct(), "suffix-docs")
    some = docs.join(maybe_broadcast(wanted, wanted.count()), "doc_id", "left_semi")

    def place(batches):
        for b in batches:
            key = (_doc_key(b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)) % K.U(buckets)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(key), *b.columns], ["bucket", "doc_id", "text", "tag"])

    some = some.mapInArrow(place, "bucket int, doc_id long, text string, tag long")
    contexts = some.groupBy("bucket").cogroup(review.select("bucket", "blob").groupBy("bucket")).applyInArrow(K.lean_cogroup(_fetch(length, q, buckets)), ROW)
    spans = contexts.groupBy("bucket").applyInArrow(K.lean_group(_order(length, q, buckets)), ROW)
    covers = named.where(F.col("kind") == COVER).unionByName(spans)
    runs = materialise(covers.groupBy("bucket").applyInArrow(K.lean_group(_runs(length, q)), "doc_id long, tag long, runs binary"), "suffix-runs")
    discard(named, wanted)
    return runs


def _tag(text) -> F.Column:
    """Hash that tells texts of one id apart, never 0."""
    return F.xxhash64(text).bitwiseOR(F.lit(1).cast("long"))


def with_runs(docs: DataFrame, runs: DataFrame) -> DataFrame:
    """docs with their runs as last column, under a name that docs lack; runs are broadcast if they are small, else both sides are shuffled."""
    size = runs.agg(F.sum(F.octet_length("runs") + 32)).first()[0] or 0
    d, r = docs.alias("d"), (F.broadcast(runs) if size <= BROADCAST_BYTES else runs).alias("r")
    own = (F.col("r.tag") == 0) | (F.col("r.tag") == _tag(F.coalesce(F.col("d.text").cast("string"), F.lit(""))))
    free = "runs" + "_" * (1 + max(map(len, docs.columns)))
    return d.join(r, (F.col("d.doc_id") == F.col("r.doc_id")) & own, "left").select("d.*", F.col("r.runs").alias(free))


def kept_parts(data: bytes, runs: bytes | None) -> tuple[bytes, int, int]:
    """(remaining bytes, removed bytes, removed runs)."""
    if runs is None:
        return data, 0, 0
    out, at, n = [], 0, 0
    for a, b in np.frombuffer(runs, "<i4").reshape(-1, 2).tolist():
        if a < len(data):
            out.append(data[at:a])
            at = min(b, len(data))
            n += 1
    out.append(data[at:])
    rest = b"".join(out)
    return rest, len(data) - len(rest), n


def _digests(batches):
    for batch in batches:
        data, offsets = K.raw(batch.column(1))
        runs = batch.column(2).to_pylist()
        n, gone, spans, sha = [], [], [], []
        for i, r in enumerate(runs):
            own = data[offsets[i] : offsets[i + 1]].tobytes()
            rest, g, s = kept_parts(own, r)
            n.append(len(own))
            gone.append(g)
            spans.append(s)
            sha.append(hashlib.sha256(rest).hexdigest())
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(spans, pa.int64()), pa.array(sha, pa.string())],
            ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"],
        )


def suffix_dedup(docs: DataFrame, length: int = LENGTH, q: int = GRAM) -> DataFrame:
    """Digest of what stays of every document."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    both = with_runs(docs, repeated_runs(docs, length, q))
    return both.mapInArrow(K.lean(_digests), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def cut_repeats(docs: DataFrame, length: int = LENGTH, q: int = GRAM) -> DataFrame:
    """docs with the repeated passages taken out of text (and n_chars set); emptied documents go.

    A character of which a part is removed is dropped, so the text stays valid.
    """
    names = docs.columns
    both = with_runs(docs, repeated_runs(docs, length, q))

    def run(batches):
        for b in batches:
            data, offsets = K.raw(b.column(names.index("text")))
            text, keep = [], []
            for i, r in enumerate(b.column(len(names)).to_pylist()):
                own = data[offsets[i] : offsets[i + 1]].tobytes()
                rest, gone, _ = kept_parts(own, r)
                text.append(rest.decode("utf-8", "ignore"))
                keep.append(not gone or bool(text[-1].strip()))
            null = b.column(names.index("text")).is_null().to_numpy(zero_copy_only=False)
            cols = {c: b.column(i) for i, c in enumerate(names)}
            cols["text"] = pa.array([None if z else t for t, z in zip(text, null, strict=True)], pa.string())
            if "n_chars" in cols:
                cols["n_chars"] = pa.array([None if z else len(t) for t, z in zip(text, null, strict=True)], cols["n_chars"].type)
            yield pa.RecordBatch.from_pydict(cols).filter(pa.array(keep))

    return both.mapInArrow(K.lean(run), docs.schema)


def op2_difference_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without the 50-byte strings that start in an earlier one."""
    return suffix_dedup(table(spark, sf_dir, "documents"))
