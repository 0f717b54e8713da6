"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .params import P61, choose_width

FIELD_BYTES = -(-P61.bit_length() // 8)


def aare(runs: DataFrame, by: list[str]) -> DataFrame:
    """Mean of |n_hat - n| / n over runs."""
    return runs.groupBy(*by).agg(F.round(F.avg(F.abs(F.col("n_hat") - F.col("n")) / F.col("n")), 4).alias("aare"))


def accuracy_summary(runs: DataFrame, by: list[str]) -> DataFrame:
    e = (F.col("n_hat") - F.col("n")) / F.col("n")
    return runs.groupBy(*by).agg(F.count("*").alias("runs"), F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"), F.stddev_samp(e).alias("rse"), F.avg(F.abs(e)).alias("aare"))


def ratio_table(errors: DataFrame, by: list[str], to: str = "zc") -> DataFrame:
    """``by..., kind, ratio``: errors of the other kinds over that of ``to``."""
    base = errors.where(F.col("kind") == to).select(*by, F.col("aare").alias("base"))
    return errors.where(F.col("kind") != to).join(base, by).select(*by, "kind", F.round(F.try_divide("aare", "base"), 4).alias("ratio"))


def hash_ops(kind: str, n: int, m: int) -> int:
    return n * m if kind == "fz" else n


def sketch_bits(kind: str, m: int, w: int) -> int:
    """Bits of a sketch: registers take the bits of an index, arrays all of theirs."""
    return m * (w - 1).bit_length() if kind == "mr" else m * w


def comm_cost(kind: str, n: int, m: int, d: int, c: int, bits: int | None = None) -> dict[str, int]:
    """Bytes and rounds of both phases for ``kind`` zc (the protocol) or fz (the prior one).

    Online: a holder's value costs a mask share from each party and one broadcast to all; an opening is every party to
    every other; a zero test opens four values in three rounds.  First-zero arrays need a product a cell besides, its
    rounds one after the other.  Offline is what these steps use up, at two field elements a party and shared value.
    """
    w = choose_width(kind, n, m)
    k = bits or max(1, d.bit_length())
    cells, q, pair = m * w, FIELD_BYTES, c * (c - 1)
    inputs = d * (cells + 1) * 2 * c * q
    openings = 4 * cells * pair * q + 2 * pair * q
    rounds = 2 + 3 + 2
    offline = cells * (k + 1 + k + 1 + 3) * 2 * pair * q + d * (cells + 1) * 2 * c * q
    if kind == "fz":
        openings += 2 * m * (w - 1) * pair * q
        rounds += w - 1
        offline += 3 * m * (w - 1) * 2 * pair * q
    return {"w": w, "online_bytes": inputs + openings, "offline_bytes": offline, "rounds": rounds}


def cost_mr_mpc(n: int, m: int, d: int, c: int) -> dict[str, int]:
    """Registers under the same machinery: a secure maximum for each register and holder after the first.

    A comparison of registers of ``b`` bits takes ``2 b`` products of two openings each, and choosing takes one more.
    """
    w = choose_width("mr", n, m)
    b = (w - 1).bit_length()
    comparisons = m * (d - 1)
    products = comparisons * (2 * b + 1)
    return {"w": w, "comparisons": comparisons, "online_bytes": products * 2 * c * (c - 1) * FIELD_BYTES + d * (m * b + 1) * 2 * c * FIELD_BYTES, "rounds": (d - 1) * (b + 1)}


def phase_seconds(cost: dict[str, int], rtt: float, bandwidth: float, per_element: float = 2e-8) -> dict[str, float]:
    """Modelled phase times: rounds at the round-trip time, bytes at the bandwidth, and work per element."""
    run = lambda b: b / bandwidth + b / FIELD_BYTES * per_element
    return {"online": cost["rounds"] * rtt + run(cost["online_bytes"]), "offline": 2 * rtt + run(cost["offline_bytes"])}


def timed(df: DataFrame) -> float:
    """Seconds of a full run into a sink that keeps nothing."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def plan_shape(df: DataFrame) -> dict[str, int]:
    """Exchanges, broadcasts and Python steps of the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange hashpartitioning") + text.count("Exchange SinglePartition"), "broadcasts": text.count("BroadcastExchange"), "python": text.count("Python") + text.count("Pandas")}
