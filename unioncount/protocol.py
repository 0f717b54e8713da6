"""The private union count: sketches, shares, secure merge, noise, checked release.

Shares, MACs, masks and openings are computed as the parties would compute them, inside one cluster; the cluster does
not keep the parties from seeing each other's slots.  The offline phase is written once, to the shared folder; the online
phase reads it, and aborts (releases nothing) if any opened value fails its check.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import field, privacy, shares
from .estimate import is_clamped, zc_estimate
from .noise import draw, noise_per_holder
from .params import ProtocolConfig
from .shares import Keys, Shared
from .sketches import merge, zc_sketch, zero_total
from .storage import written
from .zerotest import deal_tests, run_tests, test_bits

#: A dishonest party, for tests: what it does with its share of a value at a named step of a given cell.
Cheat = Callable[[str, Shared], Shared]


def offline_setup(cfg: ProtocolConfig) -> Keys:
    """The MAC keys; the prime, widths and hash key are part of the configuration."""
    if cfg.c < 2:
        raise ValueError("two computing parties at least")
    with field.using(cfg.prime):
        return Keys.agree(cfg.c, cfg.seed)


@dataclass
class Material:
    """What the offline phase hands out: masks of the holders' inputs and of their noise, and what zero tests use up."""

    masks: DataFrame
    noise_masks: DataFrame
    tests: DataFrame
    seconds: float = 0.0


def offline_phase(names: DataFrame, cfg: ProtocolConfig, keys: Keys, holders: int, keep: bool = True) -> Material:
    """Material for the holders of ``names (holder)``; written once unless ``keep`` is false.  Its size is holders x
    cells, whatever the number of elements."""
    began = time.perf_counter()
    spark, p = names.sparkSession, cfg.sketch
    held = written if keep else lambda df, _: df
    with field.using(cfg.prime):
        every = names.select("holder").distinct().crossJoin(spark.range(p.m).select(F.col("id").cast("int").alias("arr")))
        unique = F.concat_ws("|", "holder", F.col("arr").cast("string"))
        drawn = every.withColumn("mask_", F.transform(F.sequence(F.lit(0), F.lit(p.w - 1)), lambda t: shares.seeded(F.concat_ws("|", unique, t.cast("string")), cfg.seed, "in|mask")))
        masks = held(drawn.withColumn("s_", shares.deal_list(F.col("mask_"), unique, keys, cfg.seed, "in|share")), "masks")
        value, mask = shares.deal_mask(F.col("holder"), keys, cfg.seed, "noise")
        noise_masks = held(names.select("holder").distinct().select("holder", value.alias("mask_"), mask.column().alias("s_")), "noise-masks")
        grid = spark.range(p.m * p.w).select(F.col("id").alias("cell"))
        tests = held(deal_tests(grid, test_bits(holders), keys, cfg.seed, "zt"), "tests")
    return Material(masks, noise_masks, tests, time.perf_counter() - began)


def _steps(cheat: Cheat | None, step: str, x: Shared, here: Column) -> Shared:
    if cheat is None:
        return x
    bad = cheat(step, x)
    return Shared(F.when(here, bad.val).otherwise(x.val), F.when(here, bad.mac).otherwise(x.mac))


def collect_inputs(sketch: DataFrame, cfg: ProtocolConfig, keys: Keys, material: Material) -> DataFrame:
    """``cell, arr, bit, count``: shares of how many holders have each cell set.  Zeros are shared too, or the pattern
    would leak.  A holder tells all parties its bit less its mask, which they add to their shares."""
    w = cfg.sketch.w
    mine = material.masks.join(sketch.select("holder", "arr", "bits"), ["holder", "arr"], "left")
    bits = F.coalesce("bits", F.lit(0).cast("bigint"))
    told = F.transform("mask_", lambda m, t: field.sub(F.call_function("shiftright", F.array(bits)[0], t).bitwiseAND(F.lit(1)).cast("decimal(38,0)"), m))
    moved = F.zip_with("s_", told, lambda s, k: shares.add_public(Shared(s["val"], s["mac"]), k, keys).column())
    rows = mine.select("arr", F.posexplode(moved).alias("bit", "count")).withColumn("cell", F.col("arr").cast("bigint") * w + F.col("bit"))
    return shares.sum_shares(rows, ["cell", "arr", "bit"], "count", cfg.c)


def secure_merge(sketch: DataFrame, cfg: ProtocolConfig, keys: Keys, holders: int, material: Material | None = None, cheat: Cheat | None = None) -> DataFrame:
    """``cell, arr, bit, b, ok, sigma, seen``: shares of the union's bits from the holders' shared bits, with what the
    tests opened (``seen``) and each party's residual of its check (``sigma``)."""
    with field.using(cfg.prime):
        material = material or offline_phase(sketch, cfg, keys, holders, keep=False)
        counts = collect_inputs(sketch, cfg, keys, material)
        counts = counts.withColumn("count", _steps(cheat, "count", Shared.of("count"), F.col("cell") == 0).column()) if cheat else counts
        merged = run_tests(counts.join(material.tests, "cell"), "count", "b", test_bits(holders), keys, cfg.seed, "zt")
        merged = merged.withColumn("b", _steps(cheat, "bit", Shared.of("b"), F.col("cell") == 0).column()) if cheat else merged
    return merged.select("cell", "arr", "bit", "b", F.col("b_ok").alias("ok"), F.col("b_sigma").alias("sigma"), F.col("b_seen").alias("seen"))


def release_statistic(merged: DataFrame, noise: DataFrame, cfg: ProtocolConfig, keys: Keys, material: Material | None = None, cheat: Cheat | None = None) -> DataFrame:
    """``z_noisy, mac_ok, opened``: the number of zero bits plus all holders' noise, the only value that is opened.

    It is the public number of cells, less the shared sum of ones, plus the shared noise.  One aggregate adds up the
    bits and the residuals of all tests; the check is one for all openings.  If it fails, ``z_noisy`` is null.
    """
    p, c = cfg.sketch, cfg.c
    with field.using(cfg.prime):
        sums = merged.agg(shares.share_sum("b", c).alias("b"), shares.residual_sum("sigma", c).alias("sigma"), F.sum(F.size("seen")).alias("opened"))
        if material is None:
            value, mask = shares.deal_mask(F.col("holder"), keys, cfg.seed, "noise")
            masked = noise.select("noise", value.alias("mask_"), mask.column().alias("s_"))
        else:
            masked = noise.join(material.noise_masks, "holder")
        told = field.sub(field.reduce_(F.col("noise").cast("decimal(38,0)")), F.col("mask_"))
        drawn = masked.select(shares.add_public(Shared.of("s_"), told, keys).column().alias("n"))
        total = drawn.agg(shares.share_sum("n", c).alias("n"))
        both = sums.crossJoin(total)
        if cheat:
            both = both.withColumn("n", _steps(cheat, "noise", Shared.of("n"), F.lit(True)).column())
        stat = shares.add_public(shares.add(shares.scale(Shared.of("b"), field.constant(-1)), Shared.of("n")), field.constant(p.m * p.w), keys)
        both = both.withColumn("s", _steps(cheat, "statistic", stat, F.lit(True)).column()).withColumn("o", shares.open_(Shared.of("s")))
        last = shares.batched([(Shared.of("s"), F.col("o"))], F.lit("release"), keys, cfg.seed, "check")
        ok = shares.cancels(F.zip_with("sigma", last, lambda a, b: field.add(a, b)))
        return both.select(F.when(ok, field.decode_centered(F.col("o"))).alias("z_noisy"), ok.alias("mac_ok"), (F.col("opened") + 1).alias("opened"))


def estimate_row(stat: DataFrame, cfg: ProtocolConfig) -> DataFrame:
    """Adds the estimate; without a released statistic there is none."""
    p = cfg.sketch
    z = F.col("z_noisy")
    there = lambda x: F.when(z.isNotNull(), x)
    return stat.select("z_noisy", there(F.round(zc_estimate(z, p.m, p.w), 4)).alias("n_hat"), *[c for c in stat.columns if c != "z_noisy"], there(is_clamped(z, p.m, p.w)).alias("clamped"))


def counted_bytes(material: Material, opened: Column, cfg: ProtocolConfig) -> tuple[DataFrame, Column]:
    """What the phases send, counted over the rows of their tables: a frame ``dealt, inputs`` (shared values), and the
    online bytes given the number of openings.

    A dealt value costs every party an element and its MAC from every other; a mask goes to one holder, whose
    difference goes to every party; an opening is every party to every other, and so is the check.
    """
    q, c = -(-cfg.prime.bit_length() // 8), cfg.c
    dealt = material.tests.agg(F.sum(F.size("one_") + F.size("bits_") + F.size("powers_")).alias("dealt"))
    inputs = material.masks.agg(F.sum(F.size("s_")).alias("masks")).crossJoin(material.noise_masks.agg(F.count("*").alias("own"))).select((F.col("masks") + F.col("own")).alias("inputs"))
    counts = dealt.crossJoin(inputs).select(
        (F.col("dealt") * (2 * c * (c - 1) * q) + F.col("inputs") * (2 * c * q)).cast("bigint").alias("offline_bytes"), (F.col("inputs") * (2 * c * q)).cast("bigint").alias("input_bytes")
    )
    return counts, (F.col("input_bytes") + (opened + 1) * (c * (c - 1) * q)).cast("bigint")


def noise_of(df: DataFrame, cfg: ProtocolConfig, noise: str) -> DataFrame:
    """``holder, noise``: ``distributed`` is one draw for each holder, ``central`` one draw that the first holder adds
    for all, ``none`` is zero for each."""
    names = df.select("holder").distinct()
    if noise == "distributed":
        return noise_per_holder(df, cfg.sigma, cfg.seed)
    if noise == "central":
        return draw(names.agg(F.min("holder").alias("holder")), F.lit("central"), cfg.seed, cfg.sigma)
    if noise == "none":
        return names.select("holder", F.lit(0).cast("bigint").alias("noise"))
    raise ValueError(f"noise is distributed, central or none, not {noise}")


def level_of(cfg: ProtocolConfig, noise: str, holders: int) -> float | None:
    """Concentrated level of a release: of the sum of the holders' draws, of one draw, or none."""
    return {"distributed": privacy.eps_distributed(cfg.sigma, holders)[0], "central": 1 / cfg.sigma, "none": None}[noise]


def run_puc(df: DataFrame, cfg: ProtocolConfig, holders: int, draws: DataFrame | None = None, noise: str = "distributed", cheat: Cheat | None = None, report: dict | None = None) -> DataFrame:
    """One row ``z_noisy, n_hat, mac_ok, eps_c, online_bytes, offline_bytes, clamped``.

    ``holders`` is public and bounds the counts of the zero test.  A false ``mac_ok`` means that the parties abort:
    statistic and estimate are null.  ``report`` takes the seconds of both phases; the row is then computed at once.
    """
    keys = offline_setup(cfg)
    material = offline_phase(df, cfg, keys, holders)
    began = time.perf_counter()
    drawn = draws if draws is not None else noise_of(df, cfg, noise)
    stat = release_statistic(secure_merge(zc_sketch(df, cfg.sketch), cfg, keys, holders, material, cheat), drawn, cfg, keys, material, cheat)
    counts, online = counted_bytes(material, F.col("opened"), cfg)
    row = stat.crossJoin(counts).select("z_noisy", "mac_ok", F.lit(level_of(cfg, noise, holders)).cast("double").alias("eps_c"), online.alias("online_bytes"), "offline_bytes")
    out = estimate_row(row, cfg)
    if report is not None:
        out = written(out, "release")
        report |= {"offline_s": material.seconds, "online_s": time.perf_counter() - began}
    return out


def run_plain(df: DataFrame, cfg: ProtocolConfig, draws: DataFrame | None = None, noise: str = "distributed") -> DataFrame:
    """The same release without shares: equal seeds give the equal row (``z, noise, z_noisy, n_hat, clamped``)."""
    z = zero_total(merge(zc_sketch(df, cfg.sketch)), cfg.sketch)
    drawn = draws if draws is not None else noise_of(df, cfg, noise)
    stat = z.crossJoin(drawn.agg(F.coalesce(F.sum("noise"), F.lit(0)).alias("noise")))
    return estimate_row(stat.select("z", "noise", (F.col("z") + F.col("noise")).alias("z_noisy")), cfg)
