"""Step sizes, error bounds, worker limits and decay variances as plain numbers.

``constants``: ``printed`` as stated, ``derived`` as they follow from the stated inequalities (SURVEY traps T10 to T12). omega is the relative compression variance.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import exp, inf, sqrt


@dataclass(frozen=True)
class Problem:
    """Smoothness, noise, distance to the optimum, gap of the start, heterogeneity, steps, workers, compression variance."""

    smooth: float
    sigma: float
    dist: float
    gap: float
    steps: int
    workers: int
    omega: float = 0.0
    xi2: float = 0.0
    alpha: float = 1.0


def step_size(kind: str, p: Problem, constants: str = "derived") -> float:
    """Largest admissible step for plain, homogeneous or heterogeneous compressed descent, convex or nonconvex (``homog_convex`` and so on)."""
    L, M, T = p.smooth, p.workers, p.steps
    over = lambda a, b: a / b if b > 0 else inf
    k = 2 * p.omega + 1
    kh = 3 * p.omega + 1
    if kind == "plain_convex":
        return 1 / (2 * L)
    if kind == "plain_nonconvex":
        return 1 / L
    if kind == "homog_convex":
        return min(1 / (2 * L), over(M, 16 * p.omega * L), over(p.dist * sqrt(M), 2 * p.sigma * sqrt(k * T)))
    if kind == "homog_nonconvex":
        return min(1 / L, over(M, 8 * p.omega * L), over(sqrt(M), p.sigma * sqrt(k * L * T)))
    if kind == "heterog_convex":
        a = 4 * kh * p.sigma**2 + 12 * p.omega * p.xi2
        if constants == "printed":
            return min(1 / (2 * L), over(M, 16 * p.omega * L), over(p.dist * sqrt(M), sqrt(a) * T))
        return min(1 / (2 * L), over(M, 24 * p.omega * L), over(p.dist * sqrt(M), sqrt(a * T)))
    if kind == "heterog_nonconvex":
        return min(1 / L, over(M, 12 * p.omega * L), over(sqrt(M), sqrt((kh * p.sigma**2 + 3 * p.omega * p.xi2) * L * T)))
    raise ValueError(kind)


def bound(kind: str, p: Problem, constants: str = "derived") -> float:
    """Error bound at that step size; ``feedback`` is the order of error feedback with momentum."""
    L, M, T, k, kh = p.smooth, p.workers, p.steps, 2 * p.omega + 1, 3 * p.omega + 1
    root, printed = sqrt(M * T), constants == "printed"
    if kind == "plain_convex":
        eta = step_size(kind, p)
        return p.dist**2 / (2 * T * eta) + eta * p.sigma**2 / M
    if kind == "plain_nonconvex":
        eta = step_size(kind, p)
        return 2 * p.gap / (T * eta) + eta * L * p.sigma**2 / M
    if kind == "homog_convex":
        return 2 * p.dist**2 * L / T + 16 * p.omega * p.dist**2 * L / (M * T) + (2 if printed else 4) * p.sigma * p.dist * sqrt(k) / root
    if kind == "homog_nonconvex":
        return 4 * p.gap * L / T + 32 * p.omega * p.gap * L / (M * T) + 4 * p.sigma * sqrt(k * L) / root * (1 if printed else p.gap + 1)
    if kind == "heterog_convex":
        a = 4 * kh * p.sigma**2 + 12 * p.omega * p.xi2
        return 2 * p.dist**2 * L / T + (16 if printed else 24) * p.omega * p.dist**2 * L / (M * T) + (1 if printed else 2) * sqrt(a) * p.dist / root
    if kind == "heterog_nonconvex":
        return 4 * p.gap * L / T + 48 * p.omega * p.gap * L / (M * T) + 4 * sqrt((kh * p.sigma**2 + 3 * p.omega * p.xi2) * L) / root * (1 if printed else p.gap + 1)
    if kind == "feedback":
        return p.gap * L / (p.alpha * T) + p.gap * L * sqrt(p.sigma) / (sqrt(p.alpha) * T**0.75) + p.gap * L * p.sigma / root
    raise ValueError(kind)


def message_variance(p: Problem, grad2: float, mode: str = "homog") -> float:
    """Upper bound of the variance of the averaged message: homog, heterog, or tight (the cross term vanishes)."""
    s2, M = p.sigma**2, p.workers
    if mode == "tight":
        return ((p.omega + 1) * s2 + p.omega * grad2) / M
    if mode == "homog":
        return 2 * (2 * p.omega + 1) * s2 / M + 4 * p.omega / M * grad2
    return 2 * (3 * p.omega + 1) * s2 / M + 6 * p.omega * p.xi2 / M + 6 * p.omega / M * grad2


def max_workers(samples: float, method: str) -> float:
    """Workers up to which the leading term still falls, for a fixed number of samples (or a column of them): N**(1/2) for level sampling, N**(1/3) for error feedback."""
    return samples ** {"tier": 1 / 2, "feedback": 1 / 3}[method]


def decay_variance(r: float, s: int, d: int, form: str = "exact", exp=exp) -> float:
    """Relative variance of adaptive segments of s on magnitudes exp(-r j / 2): exact (s divides d), wide (r d large), or approx 4 / (r s) - 1. With the ``exp`` of columns, r and d are columns."""
    if form == "approx":
        return 4 / (r * s) - 1
    if form == "wide":
        return (1 - exp(-r * s)) / (1 - exp(-r * s / 2)) ** 2 - 1
    return (1 - exp(-r * s)) / (1 - exp(-r * d)) * ((1 - exp(-r * d / 2)) / (1 - exp(-r * s / 2))) ** 2 - 1
