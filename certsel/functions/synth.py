"""Synthetic scores: Beta(alpha, beta) by transforms of hash draws, labels drawn from the quantised score, noise, clipping."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from certsel.functions.draws import uniform
from certsel.spec import GRID

RETRIES = 4


def beta_score(key: Column, alpha: float, beta: float, seed: int = 0) -> Column:
    """beta 1: a power of one draw.  beta 2: a product of two independent powers.  beta < 1: rejection on two powers, with
    RETRIES further draws by hash (at alpha .01 under 1e-8 of the keys use them all up and keep the last one)."""
    u = lambda name: uniform(key, seed, name)
    if beta == 1:
        return F.pow(u("b1"), F.lit(1 / alpha))
    if beta == 2:
        return F.pow(u("b1"), F.lit(1 / alpha)) * F.pow(u("b2"), F.lit(1 / (alpha + 1)))
    if beta > 1:
        raise ValueError("beta is 2, 1 or below")
    out = None
    for k in reversed(range(RETRIES + 1)):
        x, v = F.pow(u(f"x{k}"), F.lit(1 / alpha)), F.pow(u(f"v{k}"), F.lit(1 / beta))
        ratio = x / (x + v)
        out = ratio if out is None else F.when(x + v <= 1, ratio).otherwise(out)
    return out


def quantised(a: Column) -> Column:
    """Null counts as 0, and scores are kept in [0, 1]."""
    a = F.coalesce(a, F.lit(0.0))
    return F.round(F.lit(1e6) * F.least(F.lit(1.0), F.greatest(F.lit(0.0), a))).cast("long")


def label(key: Column, score_u: Column, seed: int = 0) -> Column:
    return (uniform(key, seed, "label") < score_u / F.lit(float(GRID))).cast("int")


def noisy(score_u: Column, key: Column, sigma: float, seed: int = 0) -> Column:
    """Gaussian noise by the Box-Muller transform, clipped to [0, 1]."""
    z = F.sqrt(F.lit(-2.0) * F.log(uniform(key, seed, "n1"))) * F.cos(F.lit(6.283185307179586) * uniform(key, seed, "n2"))
    return quantised(score_u / F.lit(float(GRID)) + F.lit(sigma) * z)
