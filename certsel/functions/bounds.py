"""Confidence bounds of means and proportions: each returns (low, high), each side failing with probability delta."""

from __future__ import annotations

import math

import numpy as np

from certsel.spec import tail


def normal(mean: float, sd: float, k: int, delta: float) -> tuple[float, float]:
    half = tail(delta) * sd / math.sqrt(max(k, 1))
    return mean - half, mean + half


def hoeffding(mean: float, k: int, delta: float, width: float = 1.0) -> tuple[float, float]:
    half = width * math.sqrt(math.log(1 / delta) / (2 * max(k, 1)))
    return mean - half, mean + half


def bootstrap(values: np.ndarray, delta: float, replicates: int = 1000, seed: int = 0) -> tuple[float, float]:
    """Percentiles of the means of resampled draws."""
    if not len(values):
        return 0.0, math.inf
    rng = np.random.default_rng(seed)
    means = np.array([values[rng.integers(0, len(values), len(values))].mean() for _ in range(replicates)])
    return float(np.quantile(means, delta)), float(np.quantile(means, 1 - delta))


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function, by the modified Lentz scheme."""
    tiny = 1e-300
    c, d = 1.0, 1 / (1 - (a + b) * x / (a + 1) or tiny)
    out = d
    for m in range(1, 500):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / ((1 + num * d) or tiny)
            c = (1 + num / c) or tiny
            out *= c * d
        if abs(c * d - 1) < 1e-14:
            break
    return out


def beta_cdf(a: float, b: float, x: float) -> float:
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x < (a + 1) / (a + b + 2):
        return front * _beta_fraction(a, b, x) / a
    return 1 - front * _beta_fraction(b, a, 1 - x) / b


def _solve(f, target: float, low: float, high: float) -> float:
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if f(mid) < target else (low, mid)
    return (low + high) / 2


def clopper_pearson(hits: int, k: int, delta: float) -> tuple[float, float]:
    """Exact binomial bounds."""
    low = 0.0 if hits == 0 else _solve(lambda p: beta_cdf(hits, k - hits + 1, p), delta, 0, 1)
    high = 1.0 if hits == k else _solve(lambda p: beta_cdf(hits + 1, k - hits, p), 1 - delta, 0, 1)
    return low, high


def student_quantile(p: float, df: float) -> float:
    if p < 0.5:
        return -student_quantile(1 - p, df)
    return _solve(lambda t: 1 - beta_cdf(df / 2, 0.5, df / (df + t * t)) / 2, p, 0, 1e4)


def student(mean: float, sd: float, k: int, delta: float) -> tuple[float, float]:
    if k < 2:
        return -math.inf, math.inf
    half = student_quantile(1 - delta, k - 1) * sd / math.sqrt(k)
    return mean - half, mean + half


def split(delta: float, plan: str, tests: int = 1) -> float:
    """Share of delta for one bound: recall uses two, a grid one per test, two stages half for each."""
    return {"recall": delta / 2, "grid": delta / tests, "stage1": delta / 2, "stage2": delta / (2 * tests)}[plan]
