"""Counts and protocols to compare with."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import field, shares
from .hashing import hash60, uniform
from .params import ProtocolConfig, SketchParams
from .protocol import offline_phase, offline_setup, secure_merge
from .shares import Shared
from .sketches import fz_sketch
from .storage import written


def exact_union(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.count_distinct("element").alias("n"))


def sum_local(df: DataFrame) -> DataFrame:
    """``n_sum``: local distinct counts added up; counts an element once for every holder that has it."""
    return df.groupBy("holder").agg(F.count_distinct("element").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_sum"))


def run_fz_mpc(df: DataFrame, cfg: ProtocolConfig, holders: int, cheat=None) -> DataFrame:
    """First-zero sketch under the same sharing, without noise: ``z_star, mac_ok``; nothing is released if a check fails.

    The index of an array's lowest zero is the sum of its prefix products of bits, so each array takes ``w - 1``
    products one after the other: a fold over the list of its bits, with a dealt triple each.
    """
    keys, p, c = offline_setup(cfg), cfg.sketch, cfg.c
    sketch = fz_sketch(df, p)
    material = offline_phase(df, cfg, keys, holders)
    merged = secure_merge(sketch, cfg, keys, holders, material, cheat)
    with field.using(cfg.prime):
        grid = df.sparkSession.range(p.m).select(F.col("id").cast("int").alias("arr"))
        each = F.sequence(F.lit(1), F.lit(p.w - 1))
        draw = lambda kind: F.transform(each, lambda x: shares.seeded(F.concat_ws("|", F.col("arr").cast("string"), x.cast("string")), cfg.seed, f"prefix{kind}"))
        secret = grid.withColumns({"u": draw("u"), "v": draw("v")}).withColumn("uv", F.zip_with("u", "v", lambda a, b: field.mul(a, b)))
        triples = written(secret.select("arr", *[shares.deal_list(F.col(x), F.col("arr"), keys, cfg.seed, f"prefixshare{x}").alias(x) for x in ("u", "v", "uv")]), "triples")
        lists = merged.groupBy("arr").agg(F.array_sort(F.collect_list(F.struct("bit", "b"))).alias("bits"), shares.residual_sum("sigma", c).alias("sigma"), F.sum(F.size("seen")).alias("opened"))
        rows = lists.join(triples, "arr").withColumn("bits", F.transform("bits", lambda b: b["b"]))
        start = F.struct(rows["bits"][0]["val"].alias("yv"), rows["bits"][0]["mac"].alias("ym"), rows["bits"][0]["val"].alias("tv"), rows["bits"][0]["mac"].alias("tm"), rows["sigma"].alias("sigma"))

        def step(acc: Column, x: Column) -> Column:
            y, seen = shares.multiply_dealt(Shared(acc["yv"], acc["ym"]), shares.at(F.col("bits"), x), *[shares.at(F.col(k), x - 1) for k in ("u", "v", "uv")], keys)
            check = shares.batched(seen, F.concat_ws("|", F.col("arr").cast("string"), x.cast("string")), keys, cfg.seed, "prefixcheck")
            t = shares.add(Shared(acc["tv"], acc["tm"]), y)
            return F.struct(y.val.alias("yv"), y.mac.alias("ym"), t.val.alias("tv"), t.mac.alias("tm"), F.zip_with(acc["sigma"], check, lambda a, b: field.add(a, b)).alias("sigma"))

        done = rows.withColumn("end", F.aggregate(each, start, step)).select(F.struct(F.col("end.tv").alias("val"), F.col("end.tm").alias("mac")).alias("t"), F.col("end.sigma").alias("sigma"))
        total = done.agg(shares.share_sum("t", c).alias("t"), shares.residual_sum("sigma", c).alias("sigma")).withColumn("o", shares.open_(Shared.of("t")))
        last = shares.batched([(Shared.of("t"), F.col("o"))], F.lit("release"), keys, cfg.seed, "check")
        ok = shares.cancels(F.zip_with("sigma", last, lambda a, b: field.add(a, b)))
        return total.select(F.when(ok, F.col("o").cast("bigint")).alias("z_star"), ok.alias("mac_ok"))


def local_and_union(df: DataFrame) -> DataFrame:
    """``n_sum, n``: local distinct counts added up, and the union, from one pass over the distinct pairs."""
    each = df.select("holder", "element").distinct().groupBy("element").agg(F.count("*").alias("k"))
    return each.agg(F.coalesce(F.sum("k"), F.lit(0)).alias("n_sum"), F.count("*").alias("n"))


def bins_estimate(df: DataFrame, bins: int, coins: int, key: str = "k", seed: str = "s") -> DataFrame:
    """``occupied, noise, n_hat``: occupied hash bins plus fair coins, inverted for collisions.

    The coins stand for the noise bins of the parties; half of them is taken off again.
    """
    places = df.select((hash60(F.col("element"), key) % bins).alias("b")).distinct().agg(F.count("*").alias("occupied"))
    flips = df.sparkSession.range(coins).select(F.when(uniform(F.col("id").cast("string"), seed) < 0.5, 1).otherwise(0).alias("c"))
    both = places.crossJoin(flips.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("noise")))
    seen = F.greatest(F.lit(0.0), F.least(F.lit(bins - 1.0), F.col("occupied") + F.col("noise") - coins / 2))
    return both.select("occupied", "noise", F.round(-float(bins) * F.log(1 - seen / float(bins)), 4).alias("n_hat"))


def coins_for(eps: float, delta: float) -> int:
    """Fair coins that hide one bin at (eps, delta)."""
    return math.ceil(64 * math.log(2 / delta) / eps**2)


def sortcmp_exact(df: DataFrame, ranges: int | None = None, rows: int = 250_000) -> DataFrame:
    """``n``: sort by hash and count the places where the neighbour differs, range by range; equal elements share one.
    A range has about ``rows`` rows, so their number grows with the input."""
    ranges = ranges or max(64, -(-df.count() // rows))
    h = hash60(F.col("element"), "k")
    placed = df.select("element", h.alias("h")).select("element", "h", (F.col("h") / float(1 << 60) * ranges).cast("int").alias("part"))
    before = F.lag("element").over(Window.partitionBy("part").orderBy("h", "element"))
    return placed.select(F.when(before.isNull() | (before != F.col("element")), 1).otherwise(0).alias("new")).agg(F.coalesce(F.sum("new"), F.lit(0)).alias("n"))


def sortcmp_comparators(n: int) -> int:
    """Comparators of a bitonic network on the next power of two, and the neighbour tests."""
    k = max(1, math.ceil(math.log2(max(2, n))))
    return (1 << k) // 2 * k * (k + 1) // 2 + (1 << k) - 1


def sortcmp_network(df: DataFrame) -> DataFrame:
    """``n, comparators``: a bitonic network over the hashes of all rows, and a test of each neighbour, as a fold over its
    stages whose access pattern depends on the number of rows alone.  What parties would compare in secret is compared
    here in the clear; each comparator is counted.  For some thousands of rows: the list lies in one row.
    """
    spark = df.sparkSession
    hashes = df.select(hash60(F.col("element"), "k").alias("h")).agg(F.collect_list("h").alias("h"))
    n = df.count()
    k = max(1, math.ceil(math.log2(max(2, n))))
    size = 1 << k
    stages = spark.createDataFrame([([(1 << a, 1 << b) for a in range(1, k + 1) for b in range(a - 1, -1, -1)],)], "stages array<struct<span:int,gap:int>>")
    most = F.lit((1 << 62) - 1)
    rows = hashes.crossJoin(F.broadcast(stages)).withColumn("h", F.concat("h", F.array_repeat(most, F.lit(size) - F.size("h"))))

    def stage(acc: Column, s: Column) -> Column:
        def one(x: Column, i: Column) -> Column:
            other = i.bitwiseXOR(s["gap"])
            y = F.element_at(acc["h"], other + 1)
            return F.when((i < other) == (i.bitwiseAND(s["span"]) == 0), F.least(x, y)).otherwise(F.greatest(x, y))

        return F.struct(F.transform(acc["h"], one).alias("h"), (acc["used"] + size // 2).alias("used"))

    done = rows.select(F.aggregate("stages", F.struct(F.col("h").alias("h"), F.lit(0).cast("bigint").alias("used")), stage).alias("r"))
    differs = F.zip_with(F.slice("r.h", 1, size - 1), F.slice("r.h", 2, size - 1), lambda a, b: F.when((a != b) & (b < most), 1).otherwise(0))
    first = F.when(F.element_at("r.h", 1) < most, 1).otherwise(0)
    return done.select((first + F.aggregate(differs, F.lit(0), lambda a, b: a + b)).cast("bigint").alias("n"), (F.col("r.used") + size - 1).cast("bigint").alias("comparators"))


def builtin_estimates(df: DataFrame, rsd: float = 0.02) -> DataFrame:
    """Spark's own estimators on the same elements."""
    return df.agg(F.approx_count_distinct("element", rsd).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("element")).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg("element")).alias("theta"), F.count_distinct("element").alias("n_true"))

