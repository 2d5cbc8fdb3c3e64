"""Quantities of the theory: signal, rates, bounds."""

from __future__ import annotations

import math

from . import tuning


def signal_profile(n: int, z: int) -> list[float]:
    """The noise-free CUSUM of a unit step after z, at 1..n-1; it peaks at z."""
    return [math.sqrt(t / (n * (n - t))) * (n - z) if t <= z else math.sqrt((n - t) / (n * t)) * z for t in range(1, n)]


def signal_peak(n: int, z: int, size: float) -> float:
    return size * math.sqrt(z * (n - z) / n)


def operator_norm(n: int, z: int, size: float) -> float:
    """Of the rank-one signal CUSUM; at least n * tau * size / 4."""
    return size * math.sqrt(sum(x * x for x in signal_profile(n, z)))


def direction_rate(lam: float, k: int, n: int, tau: float, size: float, overlap: int = 1) -> float:
    """Bound on the sine of the angle between estimated and true direction."""
    return 32 * math.sqrt(overlap) * lam * math.sqrt(k) / (math.sqrt(n) * tau * size)


def simplified_rate(k: int, s: int, groups: int, n: int, tau: float, size: float, sigma: float = 1.0) -> float:
    return math.sqrt(sigma**2 * (k + s * math.log(groups * n)) / (n * tau**2 * size**2))


def phase_transition(groups: int, n: int) -> float:
    """The least group size beyond which larger groups no longer help at fixed k."""
    return math.log(groups * n)


def lower_bound(k: int, s: int, groups: int, n: int, tau: float, size: float, sigma: float = 1.0) -> tuple[float, bool]:
    """The rate no method beats, with its constant, and whether its condition on k, s and the groups holds."""
    root = math.sqrt(sigma**2 * (k + s * math.log(groups / s)) / (n * tau * size**2))
    return min(1 / 72, root / (72 * math.sqrt(3))), min(k, (s - 1) * math.log(groups / s)) >= 20


def location_rate(n: int, size: float, sigma: float = 1.0) -> tuple[float, float]:
    """(bound on |z_hat - z| / n up to a constant, probability it holds with) under sample splitting."""
    return sigma**2 * tuning.lambda_univariate(n) / (n * size**2), max(0.0, 1 - 20 * math.log(n) / n)


def null_tail(delta: float, n: int, groups: int) -> float:
    """Bound on the chance that noise alone exceeds the level for delta."""
    return (n - 1) * groups * delta


def norm_bound(overlap: int, n: int, sizes: list[int], frobenius: float) -> float:
    """Upper bound of the group norm of a matrix with n columns and rows in groups of these sizes."""
    return math.sqrt(overlap * n * sum(sizes)) * frobenius


def perturbation_bound(lam: float, overlap: int, n: int, k: int, gap: float) -> tuple[float, float]:
    """Bounds on the distance of the solution from the unit signal, and on the sine of the angle."""
    base = lam * math.sqrt(overlap * n * k) / gap
    return 4 * base, 8 * base
