"""Sample sizes of the guarantees. Only orders are known, so the constant c is explicit."""

from __future__ import annotations

from math import ceil, log


def _check(eps: float, delta: float) -> None:
    if not 0 < eps < 1 or not 0 < delta < 1:
        raise ValueError("eps and delta lie between 0 and 1")


def plan_generic(task: str, eps: float, delta: float, zeta: float, total: float, d: int, k: int = 1, c: float = 1.0) -> int:
    """From the sensitivity gap and the total of scores; eps and delta below 1/2."""
    if not 0 < eps < 0.5 or not 0 < delta < 0.5:
        raise ValueError("eps and delta lie between 0 and 1/2")
    size = d * d if task == "regression" else d * k
    return ceil(c * eps**-2 * zeta * total * (size * log(max(zeta * total, 2)) + log(1 / delta)))


def plan_regression(eps: float, delta: float, gamma: float, d: int, c: float = 1.0) -> int:
    _check(eps, delta)
    return ceil(c * eps**-2 * gamma**-2 * d * (d * d * log(max(d / gamma**2, 2)) + log(1 / delta)))


def plan_kmeans(eps: float, delta: float, alpha: float, tau: float, k: int, parties: int, d: int, c: float = 1.0) -> int:
    _check(eps, delta)
    mass = alpha * tau * k * parties
    return ceil(c * eps**-2 * mass * (d * k * log(max(mass, 2)) + log(1 / delta)))


def plan_robust_regression(eps: float, beta: float, parties: int, d: int, c: float = 1.0) -> int:
    return ceil(c * (eps * beta * parties) ** -2 * d**6)


def plan_robust_kmeans(eps: float, beta: float, k: int, d: int, c: float = 1.0) -> int:
    return ceil(c * (eps * beta) ** -2 * k**5 * d)


def reduction_factor(eps: float, alpha: float = 1.0) -> float:
    """Quality of an alpha-approximate solver on an eps-coreset; the bound needs eps of at most 1/3."""
    if not 0 <= eps <= 1 / 3:
        raise ValueError("the factor holds for eps up to 1/3")
    return (1 + 3 * eps) * alpha
