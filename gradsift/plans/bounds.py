"""Terms of the convergence bounds, up to constants, and the step-size offset of the annealed trainer."""

from __future__ import annotations


def bound_distributed(t: int, d: int, k: int, sigma2: float, g: float, mu: float, smooth: float) -> tuple[float, float, float]:
    """Three terms of the smooth, strongly convex bound; the first falls with the variance only."""
    r = d / k
    return sigma2 / (mu * t), r**2 * g**2 * smooth / (mu**2 * t**2), r**3 * g**3 / (mu * t**3)


def bound_single(t: int, d: int, k: int, g: float, mu: float, smooth: float) -> tuple[float, float, float]:
    """The same on one machine: the second moment stands in the first term."""
    first, second, third = bound_distributed(t, d, k, g**2, g, mu, smooth)
    return first, second, third


def bound_sgd(t: int, g: float, mu: float, smooth: float) -> float:
    return g**2 * smooth / (mu * t)


def crossover_steps(d: int, k: int) -> float:
    """Order of the number of steps beyond which compression costs nothing: (d/k)^2."""
    return (d / k) ** 2


def min_offset(d: int, k: int, beta: float = 5.0) -> float:
    """Smallest offset of the step size 1 / (t + offset); beta must exceed 4."""
    if beta <= 4:
        raise ValueError("beta must exceed 4")
    rho = 4 * beta / ((beta - 4) * (beta + 1) ** 2)
    return 2 + d * (1 + beta) / (k * (1 + rho))


def contraction_bound(d: int, k: int) -> float:
    """Share of the squared norm that a k/d contraction may leave."""
    return 1 - k / d
