"""Communication and time of one training step per worker, in numbers sent or received.

Indices (requests for candidates, names of updated parameters) are left out unless asked for.
"""

from __future__ import annotations

import math


def comm_sketch(rows: int, cols: int, p: int, k: int, cell_bits: int = 32, d: int | None = None, include_indices: bool = False, bits=None) -> float:
    """Sketch up, p*k exact values up, k new values down; does not depend on the number of workers.

    ``bits``: of a name, where it is known (a column, say); else as many as d needs.
    """
    out = rows * cols * cell_bits / 32 + p * k + k
    if include_indices:
        out += (p * k + k) * (math.ceil(math.log2(d)) if bits is None else bits) / 32
    return out


def comm_dense(d: int) -> int:
    return 2 * d


def comm_true_top_k(d: int, k: int) -> int:
    return d + k


def comm_local(k: int, union: int) -> int:
    """k up, the union of what any worker sent down."""
    return k + union


def local_union_cap(k: int, workers: int, d: int) -> int:
    return min(k * workers, d)


def compression(d: int, rows: int, cols: int, p: int, k: int, cell_bits: int = 32) -> float:
    return comm_dense(d) / comm_sketch(rows, cols, p, k, cell_bits)


def effective_compression(factor: float, iterations: float) -> float:
    """Factor left when training takes ``iterations`` times as many steps."""
    return factor / iterations


def round_ratio(rows: int, cols: int, p: int, k: int) -> float:
    """Sketch size over what the second round sends."""
    return rows * cols / (p * k)


def theory_bits(k: int, d: int, steps: int, delta: float, workers: int, constant: float = 1.0) -> float:
    """Order of the bits of one update over all workers: k log(d T / delta) W."""
    return constant * k * math.log2(d * steps / delta) * workers


def step_time(batch: int, workers: int, flop: float, numbers: float, flops: float, bandwidth: float) -> tuple[float, float, float]:
    """(compute, communication, floor) in seconds: their larger one bounds a step from below."""
    compute, comm = batch / workers * flop / flops, numbers * 4 / bandwidth
    return compute, comm, max(compute, comm)


def rounds(method: str) -> int:
    """Request round trips of a step."""
    return {"dense": 1, "true_top_k": 1, "local_top_k": 1, "sketch_no_refetch": 1, "sketch": 2, "random_candidates": 2, "annealed": 2}[method]


#: Growth of per-worker traffic with the size of the model and the number of workers.
