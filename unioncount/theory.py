"""Moments and errors of the zero-count sketch, as scalars."""

from __future__ import annotations

import math


def rank_probs(m: int, w: int) -> list[float]:
    """Probability that an element sets cell ``x`` of a given array."""
    return [2.0 ** (-min(x + 1, w - 1)) / m for x in range(w)]


def zc_mean(n: float, m: int, w: int) -> float:
    """Mean number of zero bits."""
    return m * sum((1 - q) ** n for q in rank_probs(m, w))


def zc_var(n: float, m: int, w: int) -> float:
    """Variance of the number of zero bits: pairs of cells within an array and across arrays."""
    ps = rank_probs(m, w)
    both = lambda a, b: (1 - a - b) ** n
    single = sum((1 - q) ** n for q in ps)
    across = sum(both(a, b) for a in ps for b in ps)
    within = across - sum(both(q, q) for q in ps)
    return m * single + m * within + m * (m - 1) * across - (m * single) ** 2


def zc_pois_mean(n: float, m: int, w: int) -> float:
    return m * sum(math.exp(-n * q) for q in rank_probs(m, w))


def zc_pois_var(n: float, m: int, w: int, exact: bool = True) -> float:
    """Variance under independent cells; ``exact=False`` takes the telescoped sum, as doubling p gives the next cell."""
    if not exact:
        return m * (1 - math.exp(-n / m))
    return m * sum(math.exp(-n * q) * (1 - math.exp(-n * q)) for q in rank_probs(m, w))


def slope(n: float, m: int, w: int) -> float:
    """Derivative of the expected share of zero bits by n."""
    return -sum(q * math.exp(-n * q) for q in rank_probs(m, w)) / w


def zc_mse(n: float, m: int, w: int, noise_sd: float = 0.0) -> float:
    """Mean squared error by the delta method, with the noise that is added to the statistic."""
    return (zc_pois_var(n, m, w) + noise_sd**2) / (m * w * slope(n, m, w)) ** 2


def zc_rse(n: float, m: int) -> float:
    """Relative standard error, about 0.69 / sqrt(m) for n / m >= 3."""
    return math.log(2) / math.sqrt(m) / math.sqrt(1 - math.exp(-n / m))


def zc_rse_noisy(n: float, m: int, w: int, noise_sd: float, printed: bool = False) -> float:
    """With noise of the statistic; ``printed`` has w^2 once more under the noise, which understates the error."""
    return zc_rse(n, m) * math.sqrt(1 + noise_sd**2 / (m * w * w if printed else m))
