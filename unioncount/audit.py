"""Attacks and checks: membership inference on unnoised statistics, empirical sensitivity, tampering."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shares
from .hashing import bucket, hash60, rank
from .params import ProtocolConfig, SketchParams
from .protocol import offline_setup
from .shares import Shared
from .sketches import fz_sketch, lowest_zero, merge, zc_sketch


def placed(df: DataFrame, p: SketchParams, key: str | None = None) -> DataFrame:
    """``element, arr, x`` of distinct elements; under ``key`` if one who lacks the holders' key guesses."""
    h = hash60(F.col("element"), p.key if key is None else key, p.hash)
    return df.select("element").distinct().select("element", bucket(h, p).alias("arr"), rank(h, p).alias("x"))


def audit_membership(df: DataFrame, curious: str, p: SketchParams, guess: str | None = None) -> DataFrame:
    """``candidates, flagged, wrongly_flagged`` for a holder that knows the hash (or guesses its key) and sees the exact
    statistic.

    It adds a candidate to the union's arrays: where a cell would change, no holder can have the element.  Candidates
    are all elements that the curious holder lacks, and as many made-up ones.
    """
    union = merge(zc_sketch(df, p))
    own = df.where(F.col("holder") == curious).select("element").distinct()
    others = df.where(F.col("holder") != curious).select("element").distinct().join(own, "element", "left_anti")
    made_up = others.select(F.concat(F.lit("absent|"), "element").alias("element"))
    candidates = placed(others.union(made_up), p, guess).join(union, "arr", "left")
    empty = F.call_function("shiftright", F.coalesce("bits", F.lit(0).cast("bigint")), F.col("x")).bitwiseAND(F.lit(1)) == 0
    told = candidates.select(empty.alias("flag"), F.col("element").startswith("absent|").alias("absent"))
    return told.agg(F.count("*").alias("candidates"), F.count(F.when(F.col("flag"), 1)).alias("flagged"), F.count(F.when(F.col("flag") & ~F.col("absent"), 1)).alias("wrongly_flagged"))


def empirical_sensitivity(df: DataFrame, probes: DataFrame, p: SketchParams) -> DataFrame:
    """``kind, max_change``: greatest change of the statistic when one probe joins: zero bits, and first-zero sum."""
    union = merge(zc_sketch(df, p))
    at = placed(probes, p).join(union, "arr", "left")
    change = F.call_function("shiftright", F.coalesce("bits", F.lit(0).cast("bigint")), F.col("x")).bitwiseAND(F.lit(1)).bitwiseXOR(F.lit(1))
    zc = at.agg(F.max(change).cast("bigint").alias("max_change")).select(F.lit("zc").alias("kind"), "max_change")
    fz = merge(fz_sketch(df, p))
    one = fz_sketch(probes.select(F.col("element").alias("holder"), "element"), p)
    both = one.withColumnRenamed("bits", "new").join(fz, "arr", "left")
    before = lowest_zero(F.coalesce("bits", F.lit(0).cast("bigint")), p.w)
    after = lowest_zero(F.coalesce("bits", F.lit(0).cast("bigint")).bitwiseOR(F.col("new")), p.w)
    sums = both.groupBy("holder").agg(F.sum(after - before).alias("c")).agg(F.max("c").cast("bigint").alias("max_change"))
    return zc.union(sums.select(F.lit("fz").alias("kind"), "max_change"))


def tamper_report(df: DataFrame, cfg: ProtocolConfig) -> DataFrame:
    """``cell, cp, part, detected``: each party in turn alters its share or its MAC of each value of ``df (cell, x)``."""
    keys = offline_setup(cfg)
    shared = df.select("cell", shares.share_input(F.col("x").cast("decimal(38,0)"), F.col("cell"), keys, cfg.seed, "t").column().alias("s"))
    out = None
    for cp in range(cfg.c):
        for part in ("val", "mac"):
            bad = shared.select("cell", shares.tamper(Shared.of("s"), cp, part).column().alias("s"))
            opened = bad.withColumn("o", shares.open_(Shared.of("s")))
            row = opened.select("cell", F.lit(cp).alias("cp"), F.lit(part).alias("part"), (~shares.mac_ok(Shared.of("s"), F.col("o"), keys)).alias("detected"))
            out = row if out is None else out.union(row)
    return out
