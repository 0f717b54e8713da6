"""Noise: tables of the discrete Gaussian, reproducible draws by a range join, draws from the operating system."""

from __future__ import annotations

import math
import random
import secrets
from collections.abc import Callable
from fractions import Fraction

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .hashing import uniform


def reach(sigma: float) -> int:
    return math.ceil(12 * sigma)


def pmf_table(spark: SparkSession, sigma: float, mu: int = 0) -> DataFrame:
    """``x, pmf, cdf_lo, cdf_hi`` within 12 sigma; of fixed size, so it may be broadcast."""
    k = reach(sigma)
    weight = F.exp(-(F.pow(F.col("x") - mu, F.lit(2)) / F.lit(2 * sigma * sigma)))
    rows = spark.range(mu - k, mu + k + 1, 1, 1).select(F.col("id").alias("x")).withColumn("weight", weight)
    total = Window.partitionBy()
    up = Window.orderBy("x")
    cum = rows.select("x", (F.col("weight") / F.sum("weight").over(total)).alias("pmf"), (F.sum("weight").over(up) / F.sum("weight").over(total)).alias("cdf_hi"))
    return cum.select("x", "pmf", F.coalesce(F.lag("cdf_hi").over(up), F.lit(0.0)).alias("cdf_lo"), "cdf_hi")


def draw(rows: DataFrame, text: Column, seed: str, sigma: float, out: str = "noise") -> DataFrame:
    """Adds a discrete Gaussian draw that depends on ``text`` and ``seed`` alone: inversion by range join."""
    table = F.broadcast(pmf_table(rows.sparkSession, sigma).select(F.col("x").alias(out), "cdf_lo", "cdf_hi"))
    with_u = rows.withColumn("u_", uniform(text, seed))
    return with_u.join(table, (F.col("u_") >= F.col("cdf_lo")) & (F.col("u_") < F.col("cdf_hi"))).drop("u_", "cdf_lo", "cdf_hi")


def noise_per_holder(holders: DataFrame, sigma: float, seed: str) -> DataFrame:
    """``holder, noise``: one draw for each distinct holder."""
    return draw(holders.select("holder").distinct(), F.col("holder"), seed, sigma)


def gaussian(text: Column, seed: str, sigma: float) -> Column:
    """A continuous Gaussian that depends on ``text`` and ``seed`` alone."""
    u = (F.lit(1.0) - uniform(text, seed + "u"), uniform(text, seed + "v"))
    return F.sqrt(F.lit(-2.0) * F.log(u[0])) * F.cos(F.lit(2 * math.pi) * u[1]) * F.lit(sigma)


def _bernoulli_exp(gamma: Fraction, below: Callable[[int], int]) -> bool:
    """True with probability exp(-gamma), 0 <= gamma, by comparisons of exact fractions."""
    while gamma > 1:
        if not _bernoulli_exp(Fraction(1), below):
            return False
        gamma -= 1
    k = 1
    while below(gamma.denominator * k) < gamma.numerator:
        k += 1
    return k % 2 == 1


def exact_draw(sigma: float, below: Callable[[int], int] = secrets.randbelow) -> int:
    """Discrete Gaussian by rejection from a discrete Laplace, no floating point; ``below(n)`` gives uniform whole
    numbers, from the operating system unless told otherwise."""
    s2 = Fraction(sigma).limit_denominator(10**6) ** 2
    t = math.floor(sigma) + 1
    while True:
        u = below(t)
        if not _bernoulli_exp(Fraction(u, t), below):
            continue
        v = 0
        while _bernoulli_exp(Fraction(1), below):
            v += 1
        x = u + t * v
        negative = below(2) == 1
        if negative and x == 0:
            continue
        if _bernoulli_exp((abs(x) - s2 / t) ** 2 / (2 * s2), below):
            return -x if negative else x


def exact_sums(text: Column, sigma: Column, draws: Column) -> Column:
    """Sum of ``draws`` discrete Gaussians of deviation ``sigma``, from a generator seeded by ``text``: the noise of a run
    of a study, drawn holder by holder."""

    @F.pandas_udf("double")
    def total(texts: pd.Series, sigmas: pd.Series, counts: pd.Series) -> pd.Series:
        out = []
        for t, s, k in zip(texts, sigmas, counts, strict=True):
            below = random.Random(t).randrange
            out.append(float(sum(exact_draw(s, below) for _ in range(k))))
        return pd.Series(out, dtype="float64")

    return total(text, sigma, draws)


def os_draws(holders: DataFrame, sigma: float) -> DataFrame:
    """Draws for a release.  Write the result before use: a task that runs again would draw anew."""

    @F.pandas_udf("bigint")
    def one(names: pd.Series) -> pd.Series:
        return pd.Series([exact_draw(sigma) for _ in names], dtype="int64")

    return holders.select("holder").distinct().select("holder", one.asNondeterministic()("holder").alias("noise"))


def pmf_sql(sigma: float) -> str:
    """``x, pmf, cdf_lo, cdf_hi`` in SQL."""
    k = reach(sigma)
    return (
        f"SELECT x, wt / sum(wt) OVER () AS pmf, coalesce(lag(c) OVER (ORDER BY x), 0.0) AS cdf_lo, c AS cdf_hi FROM (SELECT x, wt, sum(wt) OVER (ORDER BY x) / sum(wt) OVER () AS c "
        f"FROM (SELECT x, exp(-(pow(x, 2) / {2 * sigma * sigma!r}::DOUBLE)) AS wt FROM (SELECT unnest(range({-k}, {k + 1})) AS x)))"
    )
