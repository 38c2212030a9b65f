"""What the error of a decoded point should be, from the coefficients' rounding alone."""

from __future__ import annotations

import math


def var_s(k: float, b: int, eps_f: float) -> float:
    """Variance of the position error on one axis, k samples into a block of b."""
    return (k * b - k * k) * eps_f**2 / (6 * b * b)


def sigma(k: float, b: int, eps_f: float) -> float:
    return math.sqrt(var_s(k, b, eps_f))


def mean_dev(s: float, dim: int) -> float:
    """Mean length of a vector of `dim` normal errors of deviation s."""
    return s * math.sqrt(2) * math.gamma((dim + 1) / 2) / math.gamma(dim / 2)


def cdf(r: float, s: float, dim: int) -> float:
    """P(length <= r)."""
    if r <= 0:
        return 0.0
    if s == 0:
        return 1.0
    u = r / s
    if dim % 2 == 0:
        return 1 - math.exp(-u * u / 2) * sum((u * u / 2) ** i / math.factorial(i) for i in range(dim // 2))
    odd, term = 0.0, u
    for i in range((dim - 1) // 2):
        odd += term
        term *= u * u / (2 * i + 3)
    return math.erf(u / math.sqrt(2)) - math.sqrt(2 / math.pi) * math.exp(-u * u / 2) * odd


def p_exceed(eps: float, k: float, b: int, eps_f: float, dim: int) -> float:
    return 1 - cdf(eps, sigma(k, b, eps_f), dim)


def mean_track_error(a: float, dim: int) -> float:
    """Mean over a long block, in units of eps, at eps_f = eps / a: the mean of sqrt(x - x^2) over [0, 1] is pi / 8."""
    return mean_dev(1.0, dim) * math.pi / 8 / math.sqrt(6) / a


def pick_a(p: float, dim: int) -> float:
    """The a at which a point in mid-block exceeds eps with probability p."""
    if dim == 2:
        return math.sqrt(-math.log(p) / 12)
    low, high = 1e-6, 1e3
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if p_exceed(1.0, 50, 100, 1 / mid, dim) > p else (low, mid)
    return high
