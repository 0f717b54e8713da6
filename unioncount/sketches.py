"""Sketches as rows: building, merging, statistics, packing.

Arrays without a set bit and registers at 0 have no row.  Building is one hash aggregate with map-side combination, so
what is shuffled is bounded by tasks x holders x arrays, whatever the number of input rows; merging is the same
aggregate without the holder.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hashing import bucket, hash60, rank, rank_of
from .params import SketchParams


def zc_sketch(df: DataFrame, p: SketchParams, by: tuple[str, ...] = ("holder",)) -> DataFrame:
    """``by..., arr, bits``: zero-count sketch; bit ``x`` of ``bits`` is cell ``x``.  Repeats need no distinct."""
    h = hash60(F.col("element"), p.key, p.hash)
    placed = df.where("element is not null").select(*by, h.alias("h")).select(*by, bucket(F.col("h"), p).alias("arr"), rank(F.col("h"), p).alias("x"))
    return placed.groupBy(*by, "arr").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("x"))).alias("bits"))


def mr_sketch(df: DataFrame, p: SketchParams, by: tuple[str, ...] = ("holder",), offset: int = 0) -> DataFrame:
    """``by..., arr, reg``: greatest rank of each array, plus ``offset`` (1 for the harmonic estimator)."""
    h = hash60(F.col("element"), p.key, p.hash)
    placed = df.where("element is not null").select(*by, h.alias("h")).select(*by, bucket(F.col("h"), p).alias("arr"), rank(F.col("h"), p).alias("x"))
    return placed.groupBy(*by, "arr").agg((F.max("x") + F.lit(offset)).cast("int").alias("reg"))


def fz_sketch(df: DataFrame, p: SketchParams, by: tuple[str, ...] = ("holder",)) -> DataFrame:
    """``by..., arr, bits``: first-zero sketch; every element is hashed anew for each of the ``m`` arrays.  The fast hash
    reads the text once and mixes it with the number of each array."""
    distinct = df.where("element is not null").select(*by, "element").distinct()
    fast = p.hash == "xx64"
    told = F.xxhash64(F.lit(p.key), "element") if fast else F.col("element")
    each = distinct.select(*by, told.alias("e"), F.explode(F.sequence(F.lit(0), F.lit(p.m - 1))).alias("arr"))
    h = F.xxhash64("e", "arr") if fast else hash60(F.concat(F.col("arr").cast("string"), F.lit("|"), F.col("e")), p.key, p.hash)
    placed = each.select(*by, "arr", h.bitwiseAND(F.lit((1 << (p.w - 1)) - 1)).alias("h")).select(*by, "arr", rank_of(F.col("h"), p.w).alias("x"))
    return placed.groupBy(*by, "arr").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("x"))).alias("bits"))


def merge(sketch: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Union of sketches within ``by``; works on bits and on registers."""
    if "bits" in sketch.columns:
        return sketch.groupBy(*by, "arr").agg(F.bit_or("bits").alias("bits"))
    return sketch.groupBy(*by, "arr").agg(F.max("reg").alias("reg"))


def merge_tree(sketch: DataFrame, by: tuple[str, ...] = (), salts: int = 16) -> DataFrame:
    """The same in two levels, for more partial rows than one exchange should carry."""
    salted = sketch.withColumn("salt", F.pmod(F.xxhash64("holder"), F.lit(salts)))
    return merge(merge(salted, (*by, "salt")), by)


def zero_total(sketch: DataFrame, p: SketchParams, by: tuple[str, ...] = ()) -> DataFrame:
    """``by..., z``: zero bits over all arrays, absent ones included.  Without ``by``, one row even for no input."""
    ones = F.coalesce(F.sum(F.bit_count("bits")), F.lit(0))
    return sketch.groupBy(*by).agg((F.lit(p.m * p.w) - ones).cast("bigint").alias("z"))


def zero_by_array(sketch: DataFrame, p: SketchParams) -> DataFrame:
    """``arr, z`` for all ``m`` arrays."""
    all_arrays = sketch.sparkSession.range(p.m).select(F.col("id").cast("int").alias("arr"))
    joined = all_arrays.join(sketch.select("arr", "bits"), "arr", "left")
    return joined.select("arr", (F.lit(p.w) - F.coalesce(F.bit_count("bits"), F.lit(0))).cast("int").alias("z"))


def lowest_zero(bits: Column, w: int) -> Column:
    """Index of the lowest unset bit, ``w`` if all are set."""
    return F.least(F.bit_count(F.bitwise_not(bits).bitwiseAND(bits + 1) - 1), F.lit(w)).cast("int")


def fz_total(sketch: DataFrame, p: SketchParams, by: tuple[str, ...] = ()) -> DataFrame:
    """``by..., z_star``: sum of lowest zero indices; absent arrays add 0."""
    return sketch.groupBy(*by).agg(F.coalesce(F.sum(lowest_zero(F.col("bits"), p.w)), F.lit(0)).cast("bigint").alias("z_star"))


def register_sums(sketch: DataFrame, p: SketchParams, by: tuple[str, ...] = ()) -> DataFrame:
    """``by..., harmonic, empty, total``: sum of 2^-register, registers at 0, sum of registers, over all ``m``."""
    at_zero = F.lit(p.m) - F.count(F.when(F.col("reg") > 0, 1))
    harmonic = F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("reg"))), F.lit(0.0)) + (F.lit(p.m) - F.count("reg"))
    return sketch.groupBy(*by).agg(harmonic.alias("harmonic"), at_zero.cast("bigint").alias("empty"), F.coalesce(F.sum("reg"), F.lit(0)).cast("bigint").alias("total"))


def to_wide(sketch: DataFrame, p: SketchParams) -> DataFrame:
    """``holder, words``: one row a holder with all ``m`` arrays in order."""
    pairs = sketch.groupBy("holder").agg(F.map_from_entries(F.collect_list(F.struct("arr", "bits"))).alias("by_arr"))
    words = F.transform(F.sequence(F.lit(0), F.lit(p.m - 1)), lambda i: F.coalesce(F.element_at("by_arr", i), F.lit(0).cast("bigint")))
    return pairs.select("holder", words.alias("words"))


def from_wide(wide: DataFrame) -> DataFrame:
    return wide.select("holder", F.posexplode("words").alias("arr", "bits")).where("bits <> 0")


def fingerprint(p: SketchParams, kind: str = "zc") -> str:
    """Tells sketches of other parameters apart without giving the key away."""
    return hashlib.sha256(f"{kind}|{p.m}|{p.w}|{p.hash}|{hashlib.sha256(p.key.encode()).hexdigest()}".encode()).hexdigest()[:16]


def pack(sketch: DataFrame, p: SketchParams, kind: str = "zc") -> DataFrame:
    """``holder, fingerprint, packed``: 16 hexadecimal digits an array, as binary."""
    wide = to_wide(sketch, p)
    text = F.array_join(F.transform("words", lambda b: F.lpad(F.hex(b), 16, "0")), "")
    return wide.select("holder", F.lit(fingerprint(p, kind)).alias("fingerprint"), F.unhex(text).alias("packed"))


def unpack(packed: DataFrame, p: SketchParams, kind: str = "zc") -> DataFrame:
    """Rows of packed sketches; a foreign fingerprint raises when the rows are read."""
    known = F.when(F.col("fingerprint") == fingerprint(p, kind), F.hex("packed")).otherwise(F.raise_error(F.lit("sketch of other parameters")))
    words = F.transform(F.sequence(F.lit(0), F.lit(p.m - 1)), lambda i: F.conv(F.substring(F.col("digits"), i * 16 + 1, F.lit(16)), 16, 10).cast("bigint"))
    return from_wide(packed.select("holder", known.alias("digits")).select("holder", words.alias("words")))
