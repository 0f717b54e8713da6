"""Estimators as column expressions: no UDF and no round trip to the driver."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from .theory import rank_probs

#: Bias constants: of the first-zero sketch, and of the mean-rank estimator.
FZ_BIAS, MEAN_RANK = 0.77351, 0.783


def zc_estimate(z: Column, m: int, w: int, form: str = "exp", iters: int = 60) -> Column:
    """Cardinality at which the expected share of zero bits equals ``z / (m w)``, by bisection in [0, m 2^w].

    ``form='pow'`` takes (1 - p)^n in place of exp(-n p).  A share of 1 or more gives 0, one below the least reachable
    gives the upper end.
    """
    probs = F.array(*[F.lit(math.log1p(-q) if form == "pow" else -q) for q in rank_probs(m, w)])
    share = z / F.lit(float(m * w))

    def half(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        f = F.aggregate(probs, F.lit(0.0), lambda acc, q: acc + F.exp(mid * q)) / F.lit(float(w))
        return F.struct(F.when(f > share, mid).otherwise(s["lo"]).alias("lo"), F.when(f > share, s["hi"]).otherwise(mid).alias("hi"))

    start = F.struct(F.lit(0.0).alias("lo"), F.lit(float(m * 2**w)).alias("hi"))
    found = F.aggregate(F.sequence(F.lit(1), F.lit(iters)), start, half, lambda s: (s["lo"] + s["hi"]) / 2)
    return F.when(share >= 1, F.lit(0.0)).otherwise(found)


def zc_estimate_by_row(z: Column, m: Column, w: Column, iters: int = 60) -> Column:
    """:func:`zc_estimate` with sizes that are columns: one expression serves rows of all sizes."""
    md, wd = m.cast("double"), w.cast("double")
    rates = F.transform(F.sequence(F.lit(0), w - 1), lambda x: -F.pow(F.lit(2.0), -F.least(x + 1, w - 1)) / md)
    share = z / (md * wd)

    def half(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        f = F.aggregate(s["q"], F.lit(0.0), lambda acc, q: acc + F.exp(mid * q)) / wd
        return F.struct(F.when(f > share, mid).otherwise(s["lo"]).alias("lo"), F.when(f > share, s["hi"]).otherwise(mid).alias("hi"), s["q"].alias("q"))

    start = F.struct(F.lit(0.0).alias("lo"), (md * F.pow(F.lit(2.0), wd)).alias("hi"), rates.alias("q"))
    found = F.aggregate(F.sequence(F.lit(1), F.lit(iters)), start, half, lambda s: (s["lo"] + s["hi"]) / 2)
    return F.when(share >= 1, F.lit(0.0)).otherwise(found)


def alpha_by_row(m: Column) -> Column:
    """Bias constant of the harmonic estimator for large m, in closed form."""
    return F.lit(0.7213) / (F.lit(1.0) + F.lit(1.079) / m)


def is_clamped(z: Column, m: int, w: int) -> Column:
    return (z > m * w) | (z < 0)


def fz_estimate(z_star: Column, m: int) -> Column:
    return F.pow(F.lit(2.0), z_star / F.lit(float(m))) / F.lit(FZ_BIAS)


def alpha(m: int, steps: int = 20_000) -> float:
    """Bias constant of the harmonic estimator: 1 / (m times the integral of log2((2+u)/(1+u))^m over u >= 0).

    With u = t / (1 - t) and the midpoint rule; exact to about 1e-6 for m >= 16.
    """
    total = 0.0
    for i in range(steps):
        t = (i + 0.5) / steps
        u = t / (1 - t)
        total += math.log2((2 + u) / (1 + u)) ** m / (1 - t) ** 2
    return 1 / (m * total / steps)


def mr_estimate(harmonic: Column, empty: Column, m: int, correct: bool = True) -> Column:
    """Harmonic estimate; below 2.5 m and with empty registers, the count of these decides instead."""
    raw = F.lit(alpha(m) * m * m) / harmonic
    if not correct:
        return raw
    return F.when((raw < 2.5 * m) & (empty > 0), F.lit(-float(m)) * F.log(empty / F.lit(float(m)))).otherwise(raw)


def mr_mean_estimate(total: Column, m: int) -> Column:
    """From the mean register (ranks without offset)."""
    return F.lit(MEAN_RANK * m) * F.pow(F.lit(2.0), total / F.lit(float(m)))


def bisect_sql(base: str, keys: list[str], m: int, w: int, z: str = "z", form: str = "exp", out: str = "n_hat") -> str:
    """SQL twin of :func:`zc_estimate`: ``keys..., z, out`` (not rounded) for the rows of ``base``."""
    if form == "pow":
        terms = " + ".join(f"exp(mid * {math.log1p(-q)!r}::DOUBLE)" for q in rank_probs(m, w))
    else:
        terms = " + ".join(f"exp(mid * {-q!r}::DOUBLE)" for q in rank_probs(m, w))
    ks = "".join(k + ", " for k in keys)
    return (
        f"WITH RECURSIVE base AS ({base}), b AS (SELECT {ks}{z}, 0 AS k, 0.0::DOUBLE AS lo, {float(m * 2**w)!r}::DOUBLE AS hi FROM base UNION ALL "
        f"SELECT {ks}{z}, k + 1, CASE WHEN f > {z} / {float(m * w)!r}::DOUBLE THEN mid ELSE lo END, CASE WHEN f > {z} / {float(m * w)!r}::DOUBLE THEN hi ELSE mid END "
        f"FROM (SELECT *, (({terms}) / {float(w)!r}::DOUBLE) AS f FROM (SELECT *, (lo + hi) / 2 AS mid FROM b WHERE k < 60))) "
        f"SELECT {ks}{z}, CASE WHEN {z} >= {m * w} THEN 0.0::DOUBLE ELSE (lo + hi) / 2 END AS {out} FROM b WHERE k = 60"
    )
