"""Probability that a candidate which recurs in k distinct records identifies one entity.

With recurrence Poisson(lam) for identifying candidates, Poisson(mu) for others and a share c of
identifying ones, the posterior is 1 / (1 + a^k b) with a = mu / lam and b = e^(lam - mu) (1 - c) / c.
Everything goes through x = k ln a + ln b, so that large k cannot overflow.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def check(a: float, b: float, decreasing: bool = True) -> None:
    if a <= 0 or b <= 0 or decreasing and a <= 1:
        raise ValueError(f"need a > 1 and b > 0 for a posterior that falls with k, got a={a}, b={b}")


def exponent(k: Column, a: float, b: float) -> Column:
    return k * F.lit(math.log(a)) + F.lit(math.log(b))


def posterior(k: Column, a: float, b: float) -> Column:
    check(a, b, decreasing=False)
    return 1 / (1 + F.exp(exponent(k, a, b)))


def ln_doubt(k: Column, a: float, b: float) -> Column:
    """ln(1 - p), exact where 1 - p underflows next to 1."""
    return -F.log1p(F.exp(-exponent(k, a, b)))


def two_parameters(lam: float, mu: float, c: float) -> tuple[float, float]:
    return mu / lam, math.exp(lam - mu) * (1 - c) / c


def posterior_poisson(k: Column, lam: float, mu: float, c: float) -> Column:
    """The three-rate form, from both Poisson terms (k! cancels)."""
    mine = F.lit(math.log(c)) - lam + k * math.log(lam)
    other = F.lit(math.log(1 - c)) - mu + k * math.log(mu)
    return 1 / (1 + F.exp(other - mine))


def posterior_power(k: Column, alpha: float, c0: float) -> Column:
    """A power law in k, at most 1."""
    return F.least(F.lit(1.0), c0 * F.pow(k.cast("double"), F.lit(-alpha)))


def ln_factorial(k: Column) -> Column:
    """ln k! of a column: a product below 16, Stirling's series from there on (its error is below 1e-11)."""
    x = F.greatest(k, F.lit(16)).cast("double")
    series = x * F.ln(x) - x + 0.5 * F.ln(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * x * x * x) + 1 / (1260 * F.pow(x, F.lit(5.0)))
    small = F.element_at(F.array(*[F.lit(math.lgamma(i + 1)) for i in range(16)]), F.least(F.greatest(k, F.lit(0)), F.lit(15)).cast("int") + 1)
    return F.when(k < 16, small).otherwise(series)


def posterior_low_mean(k: Column, lam: float) -> Column:
    """The mass of a Poisson law with mean below 1, relative to its mass at k = 1."""
    return F.exp((k - 1) * math.log(lam) - ln_factorial(k))


def k_max(rho: float, a: float, b: float) -> int:
    """The largest whole k with p(k) > rho: a^k b < (1 - rho) / rho."""
    check(a, b)
    if rho <= 0:
        raise ValueError("rho = 0 keeps every candidate: no bound on k")
    bound = (math.log((1 - rho) / rho) - math.log(b)) / math.log(a) if rho < 1 else -1
    k = math.floor(bound)
    return max(0, k - 1 if abs(bound - k) < 1e-12 else k)


def fit_em(histogram: dict[int, int], rounds: int = 400) -> tuple[float, float, float]:
    """(lam, mu, c) of a mixture of two zero-truncated Poisson laws, by expectation-maximisation.

    ``histogram`` maps k >= 1 to the number of candidates that recur k times; k = 0 is never seen.
    """
    total = sum(histogram.values())
    mean = sum(k * n for k, n in histogram.items()) / total
    lam, mu, c = max(0.05, mean * 0.2), mean * 4 + 1, 0.9

    def mass(k: int, m: float) -> float:
        return k * math.log(m) - m - math.lgamma(k + 1) - math.log(-math.expm1(-m))

    def solve(target: float) -> float:
        """The rate whose zero-truncated mean is ``target``."""
        lo, hi = 1e-9, max(target, 1e-6)
        for _ in range(80):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if mid / -math.expm1(-mid) < target else (lo, mid)
        return (lo + hi) / 2

    for _ in range(rounds):
        share = {k: 1 / (1 + math.exp(min(700, math.log((1 - c) / c) + mass(k, mu) - mass(k, lam)))) for k in histogram}
        mine = sum(n * share[k] for k, n in histogram.items())
        if mine <= 0 or mine >= total:
            break
        c = min(1 - 1e-9, max(1e-9, mine / total))
        lam = solve(max(1 + 1e-9, sum(n * k * share[k] for k, n in histogram.items()) / mine))
        mu = solve(max(1 + 1e-9, sum(n * k * (1 - share[k]) for k, n in histogram.items()) / (total - mine)))
    return lam, mu, c
