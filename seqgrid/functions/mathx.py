"""Logarithms of factorials, gamma and binomials as plain column expressions, and of partition numbers on the driver.

The columns stay inside whole-stage code generation: a literal array below 18, an asymptotic series above it
(relative error below 1e-15). Python twins (``lf``, ``lg``) serve the in-memory kernel.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

_SMALL = 18
_HALF_LOG_2PI = 0.5 * math.log(2 * math.pi)


def ln_fact(x: Column) -> Column:
    """ln x! of a whole number (BIGINT or DOUBLE) >= 0."""
    table = F.array(*[F.lit(math.lgamma(i + 1)) for i in range(_SMALL)])
    # the series must not see 0 in the branch that isn't taken
    v = F.greatest(x.cast("double"), F.lit(float(_SMALL)))
    inv = 1.0 / v
    sq = inv * inv
    series = (v + 0.5) * F.log(v) - v + _HALF_LOG_2PI + inv * (1 / 12 - sq * (1 / 360 - sq * (1 / 1260 - sq / 1680)))
    return F.when(x < _SMALL, F.element_at(table, F.least(x, F.lit(_SMALL - 1)).cast("int") + 1)).otherwise(series)


def ln_gamma(x: Column) -> Column:
    """ln Gamma(x) of a whole number >= 1."""
    return ln_fact(x - 1)


def ln_binom(n: Column, k: Column) -> Column:
    """ln of n over k."""
    return ln_fact(n) - ln_fact(k) - ln_fact(n - k)


def ln_gamma_step(x: Column, y: Column) -> Column:
    """ln Gamma(x + y) - ln Gamma(x), without cancellation where x is far above y."""
    xd, yd = x.cast("double"), y.cast("double")
    big = F.greatest(xd, F.lit(1.0))
    far = (big - 0.5) * F.log1p(yd / big) + yd * F.log(big + yd) - yd + (1 / (big + yd) - 1 / big) / 12
    return F.when((xd > 1e6) & (yd < xd / 1024), far).otherwise(ln_gamma(x + y) - ln_gamma(x))


def lf(x: int | float) -> float:
    return math.lgamma(x + 1)


def lg(x: int | float) -> float:
    return math.lgamma(x)


def ln_choose(n: float, k: float) -> float:
    return lf(n) - lf(k) - lf(n - k)


_EXACT_N = 4000


def _ln_stirling_far(n: int, k: int) -> float:
    """Uniform saddle-point form of ln S(n, k) for large n."""
    if k == 1 or k == n:
        return 0.0
    ratio = n / k
    lo, hi = 1e-12, ratio
    for _ in range(200):
        mid = (lo + hi) / 2
        if mid / -math.expm1(-mid) < ratio:
            lo = mid
        else:
            hi = mid
    x, t = (lo + hi) / 2, ratio - 1
    grow = x + math.log(-math.expm1(-x))  # ln(e^x - 1)
    a = -n * math.log(x) + k * grow - k * t + (n - k) * math.log(t)
    gap = (1 + t) * (x - t)
    return 0.5 * math.log(t / gap) + a + (n - k) * math.log(k) + ln_choose(n, k) if gap > 0 else 2 * math.log(n) * (n - k) - lf(n - k) - (n - k) * math.log(2)


@lru_cache(maxsize=64)
def _stirling_row(n: int, k_max: int) -> tuple[float, ...]:
    if n > _EXACT_N:
        return tuple(_ln_stirling_far(n, k) for k in range(1, k_max + 1))
    row = np.full(k_max + 1, -np.inf)
    row[0] = 0.0
    with np.errstate(divide="ignore"):
        logs = np.log(np.arange(k_max + 1, dtype=float))
    for _ in range(n):
        nxt = np.full(k_max + 1, -np.inf)
        nxt[1:] = np.logaddexp(row[:-1], row[1:] + logs[1:])
        row = nxt
    return tuple(row[1:].tolist())


def ln_partitions(n: int, k_max: int, prior: str = "at_most") -> list[float]:
    """ln B(n, k) for k = 1..k_max: partitions of n items in at most k parts, or, with prior 'exact', in just k."""
    if prior not in ("at_most", "exact"):
        raise ValueError("prior is 'at_most' or 'exact'")
    if n < 1 or k_max < 1:
        return [0.0] * max(k_max, 0)
    row = list(_stirling_row(n, min(k_max, n)))
    if prior == "at_most":
        row = np.logaddexp.accumulate(row).tolist()
    return row + [row[-1] if prior == "at_most" else -math.inf] * (k_max - len(row))


def ln_b(n: int, k: int, prior: str = "at_most") -> float:
    return ln_partitions(n, k, prior)[k - 1] if k >= 1 else 0.0


def variable_level(n: int, a: int, big_n: int, ks: int, kt: int, ke: int, prior: str = "at_most") -> float:
    """The part of the cost that depends on the numbers of parts only."""
    if big_n == 0:
        return 0.0
    k = float(ks) * kt * ke
    return ln_b(n, ks, prior) + ln_b(a, ke, prior) + lg(big_n + k) - lg(k) - lf(big_n)
