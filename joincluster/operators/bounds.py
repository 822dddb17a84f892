"""Approximation guarantees as functions."""

from __future__ import annotations

import math

#: Best ratio known for the second solver in Euclidean space.
BEST_GAMMA = 6.357


def approx_bound(alpha: float = 1.0, gamma: float = 1.0) -> float:
    """Ratio of the method with solvers of ratios alpha (subspaces) and gamma (grid): 9 for two exact ones."""
    return (math.sqrt(alpha) + math.sqrt(gamma) + math.sqrt(alpha * gamma)) ** 2


def approx_bound_reg(alpha: float = 1.0, gamma: float = 1.0) -> float:
    """The same with a penalty: 10 for two exact solvers."""
    return 2 * alpha + 4 * gamma + 4 * alpha * gamma


def approx_lower_bound(k: int, kappa: int, m: int, corrected: bool = True) -> float:
    """How bad the method can be with too few components: uniform axes of m subspaces, k centers. corrected=False keeps the printed cube."""
    side = k ** (1 / m)
    lost = 12 * side**2 if corrected else 12 * side**3
    return math.sqrt(max(0.0, 1 - math.exp(-m / (2 * kappa)))) * math.sqrt(lost / m) / (4 * kappa)


def check_kappa(kappa: int, supports: list[int]) -> bool:
    """Whether the guarantee's condition holds: as many components as the optimum's parts have in any subspace."""
    return kappa >= max(supports, default=0)


def bound_slack(ours: float, base: float, alpha: float = 1.0, gamma: float = 1.0) -> float:
    return ours / base / approx_bound(alpha, gamma) if base > 0 else 0.0
