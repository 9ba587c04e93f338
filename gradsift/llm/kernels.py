"""Vectorised byte kernels over Arrow string columns (numpy, no per-character Python)."""

from __future__ import annotations

import ctypes
from collections.abc import Callable

import numpy as np
import pyarrow as pa

U = np.uint64
_rng = np.random.default_rng(20240607)
BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
R = U(0x9E3779B97F4A7C15)
R_INV = U(pow(int(R), -1, 2**64))
STEP = _rng.integers(1, 2**63, 64, dtype=np.uint64) * U(2) + U(1)
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def idle() -> None:
    """Gives memory that is no longer used back to the system, where its C library can."""
    if _powers and len(_powers[0]) > 1 << 20:
        _powers.clear()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def lean(run: Callable) -> Callable:
    """A ``mapInArrow`` function whose worker, which waits for further tasks, ends without spare memory."""

    def task(batches):
        yield from run(batches)
        idle()

    return task


def lean_group(run: Callable) -> Callable:
    """The same for an ``applyInArrow`` function whose groups are buckets of some MB."""

    def group(t: pa.Table) -> pa.Table:
        out = run(t)
        idle()
        return out

    return group


def lean_cogroup(run: Callable) -> Callable:
    """The same for two sides."""

    def group(left: pa.Table, right: pa.Table) -> pa.Table:
        out = run(left, right)
        idle()
        return out

    return group


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """R**i and R**-i for i < n, kept for the next call."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, 1 << 20)
        ones = np.full(size, R, dtype=np.uint64)
        ones[0] = 1
        inv = np.full(size, R_INV, dtype=np.uint64)
        inv[0] = 1
        _powers[:] = [np.cumprod(ones), np.cumprod(inv)]
    return _powers[0][:n], _powers[1][:n]


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string or binary column without copying; null: empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) else b"")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None:
        return np.zeros(0, np.uint8), offsets
    lo, hi = int(offsets[0]), int(offsets[-1])
    return np.frombuffer(data, dtype=np.uint8)[lo:hi], offsets - lo


def pieces(offsets: np.ndarray, limit: int = 1 << 20):
    """Ranges of documents of about ``limit`` bytes in all, so that temporaries stay small."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1)
        yield i, j
        i = j


def words(data: np.ndarray, offsets: np.ndarray, lower: bool = True, ends: bool = False):
    """Hash of each word and, per document, the number of its first word (len docs + 1).

    ``ends``: the place behind each word is returned too.
    """
    if not len(data):
        none = np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
        return (*none, np.zeros(0, np.int64)) if ends else none
    a = LOWER[data] if lower else data
    inside = ~IS_SPACE[a]
    edge = np.zeros(len(a) + 1, bool)
    edge[offsets] = True
    before = np.empty(len(a), bool)
    before[0] = False
    before[1:] = inside[:-1]
    start = np.flatnonzero(inside & (~before | edge[:-1]))
    after = np.empty(len(a), bool)
    after[-1] = False
    after[:-1] = inside[1:]
    end = np.flatnonzero(inside & (~after | edge[1:])) + 1
    up, down = powers(len(a) + 1)
    total = np.zeros(len(a) + 1, np.uint64)
    np.cumsum(BYTE_CODE[a] * up[:-1], out=total[1:])
    h = mix((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64))
    first = np.searchsorted(start, offsets)
    return (h, first, end) if ends else (h, first)


def shingles(h: np.ndarray, first: np.ndarray, k: int):
    """Per document the sorted distinct hashes of its k-word shingles (fewer words: one of all)."""
    if len(h) >= k:
        grams = h[: len(h) - k + 1] * STEP[0]
        for j in range(1, k):
            grams = grams + h[j : len(h) - k + 1 + j] * STEP[j]
        grams = mix(grams)
    else:
        grams = np.zeros(0, np.uint64)
    for i in range(len(first) - 1):
        a, b = int(first[i]), int(first[i + 1])
        if b - a >= k:
            yield np.unique(grams[a : b - k + 1])
        elif b > a:
            yield mix((h[a:b] * STEP[: b - a]).sum(dtype=np.uint64, keepdims=True) + U(b - a))
        else:
            yield np.zeros(0, np.uint64)


def rolling(data: np.ndarray, q: int) -> np.ndarray:
    """Hash of each run of q bytes (q a power of two), by doubling."""
    h = BYTE_CODE[data]
    size, power = 1, R
    while size < q:
        h = h[:-size] * power + h[size:]
        power = U(int(power) ** 2 % 2**64)
        size *= 2
    return mix(h)
