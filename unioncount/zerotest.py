"""Zero test on shares: from [x] to [x != 0] without revealing x.

Offline, each cell gets a shared random mask with its shared bits, a shared random factor with its inverse and powers,
and a triple for one product (``deal_tests``).  Online (``run_tests``) the masked value, two differences and a blinded
distance are opened.  Lists of bits and powers are array columns, so that the plan does not grow with them.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import field, shares
from .shares import Keys, Shared

_WIDE = "decimal(38,0)"
#: Entries of the list of single shared values that a cell is dealt.
MASK, INVERSE, U, V, UV = range(5)


def test_bits(d: int) -> int:
    """Bits that hold counts 0..d."""
    return max(1, math.ceil(math.log2(d + 1)))


def compared_bits(bits: int, variant: str) -> int:
    """``masked`` compares the bits that counts have, ``literal`` as many as the prime has."""
    return field.modulus().bit_length() if variant == "literal" else bits


def _bit(x: Column, t: Column) -> Column:
    """Bit ``t`` of a value below 2^90, as 0 or 1."""
    limb = F.lit(1 << 30).cast(_WIDE)
    low, rest = F.pmod(x, limb), x
    parts = []
    for _ in range(3):
        low = F.pmod(rest, limb)
        parts.append(low.cast("bigint"))
        rest = ((rest - low) / limb).cast(_WIDE)
    part = F.array(*parts)[(t / 30).cast("int")]
    return F.call_function("shiftright", part, (t % 30).cast("int")).bitwiseAND(F.lit(1)).cast(_WIDE)


def bits_of(x: Column, n: int) -> Column:
    return F.transform(F.array(x), lambda v: F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda t: _bit(v, t)))[0]


def deal_tests(df: DataFrame, bits: int, keys: Keys, seed: str, tag: str, variant: str = "masked", cell: str = "cell") -> DataFrame:
    """Adds what a test of each cell uses up: ``one_`` (mask, inverse, triple), ``bits_`` and ``powers_``, all shared.

    ``masked`` draws the mask from [0, p - 2^bits), so that no sum wraps.  ``literal`` draws as many bits as the prime
    has: a mask of p or more then misreads.
    """
    p, n = field.modulus(), compared_bits(bits, variant)
    at = F.col(cell)
    raw = shares.random_bits(at, seed, tag + "|a")
    mask = F.pmod(raw, field.whole(1 << n if variant == "literal" else p - (1 << bits))).cast(_WIDE)
    u, v = shares.seeded(at, seed, tag + "|gu"), shares.seeded(at, seed, tag + "|gv")
    factor = (F.pmod(shares.random_bits(at, seed, tag + "|R"), field.whole(p - 1)) + 1).cast(_WIDE)
    secret = df.withColumns({"mask__": mask, "u__": u, "v__": v, "R__": factor})
    ones = F.array(field.reduce_(F.col("mask__")), field.inverse(F.col("R__")), F.col("u__"), F.col("v__"), field.mul(F.col("u__"), F.col("v__")))
    powers = F.aggregate(F.sequence(F.lit(2), F.lit(n)), F.array(F.col("R__")), lambda acc, _: F.concat(acc, F.array(field.mul(F.element_at(acc, -1), F.col("R__"))))) if n > 1 else F.array(F.col("R__"))
    dealt = {
        "one_": shares.deal_list(ones, at, keys, seed, tag + "|one"),
        "bits_": shares.deal_list(bits_of(F.col("mask__"), n), at, keys, seed, tag + "|bit"),
        "powers_": shares.deal_list(powers, at, keys, seed, tag + "|pow"),
    }
    return secret.withColumns(dealt).drop("mask__", "u__", "v__", "R__")


def run_tests(df: DataFrame, name: str, out: str, bits: int, keys: Keys, seed: str, tag: str, variant: str = "masked", cell: str = "cell") -> DataFrame:
    """The online steps on cells that ``deal_tests`` has dealt: adds the shared column ``out``, ``out_sigma`` (one
    residual a party for all four openings) and ``out_ok``, and keeps the opened values as ``out_seen``.

    The sum of x and the mask is opened; its Hamming distance to the mask's shared bits is 0 only for x = 0.  One more
    than the distance is blinded by a random factor and opened, and the lookup polynomial is put together from shared
    powers of that factor.
    """
    n, c = compared_bits(bits, variant), len(keys.shares)
    one = F.col("one_")
    work = df.withColumn("r_", shares.add(Shared.of(name), shares.at(one, MASK)).column()).withColumn("ro_", shares.open_(Shared.of("r_")))
    work = work.withColumn("rb_", bits_of(F.col("ro_"), n))
    # a bit of the mask counts as it is where the opened bit is 0, and as 1 less it where that is 1
    sign = F.transform("rb_", lambda b: F.when(b == 1, field.constant(-1)).otherwise(field.constant(1)))
    public = field.reduce_(F.aggregate("rb_", field.constant(1), lambda acc, b: (acc + b).cast(_WIDE)))
    work = work.withColumn("h_", shares.combine(F.col("bits_"), sign, c).column()).withColumn("h1_", shares.add_public(Shared.of("h_"), public, keys).column())
    gamma, seen = shares.multiply_dealt(shares.at(one, INVERSE), Shared.of("h1_"), shares.at(one, U), shares.at(one, V), shares.at(one, UV), keys)
    work = work.withColumns({"dx_": seen[0][0].column(), "dxo_": seen[0][1], "dy_": seen[1][0].column(), "dyo_": seen[1][1]})
    work = work.withColumn("g_", gamma.column()).withColumn("go_", shares.open_(Shared.of("g_")))
    opened = [(Shared.of(x), F.col(f"{x[:-1]}o_")) for x in ("r_", "dx_", "dy_", "g_")]
    beta = F.array(*[field.constant(b) for b in field.lookup_poly(n)])
    gammas = F.aggregate(F.sequence(F.lit(2), F.lit(n)), F.array(F.col("go_")), lambda acc, _: F.concat(acc, F.array(field.mul(F.element_at(acc, -1), F.col("go_"))))) if n > 1 else F.array(F.col("go_"))
    factors = F.zip_with(F.slice(beta, 2, n), gammas, lambda b, g: field.mul(b, g))
    work = work.withColumn("b_", shares.combine(F.col("powers_"), factors, c).column())
    work = work.withColumn(out, shares.add_public(Shared.of("b_"), beta[0], keys).column())
    sigma = shares.batched(opened, F.col(cell), keys, seed, tag + "|check")
    work = work.withColumn(f"{out}_sigma", sigma).withColumn(f"{out}_ok", shares.cancels(F.col(f"{out}_sigma"))).withColumn(f"{out}_seen", F.array(*[v for _, v in opened]))
    kept = [x for x in df.columns if x not in ("one_", "bits_", "powers_")]
    return work.select(*kept, out, f"{out}_sigma", f"{out}_ok", f"{out}_seen")


def zero_test(df: DataFrame, name: str, out: str, bits: int, keys: Keys, seed: str, tag: str, variant: str = "masked", cell: str = "cell") -> DataFrame:
    """Deals and runs the tests at one go: ``out`` is 0 where ``name`` is 0 and 1 where it lies in 1..2^bits - 1."""
    return run_tests(deal_tests(df, bits, keys, seed, tag, variant, cell), name, out, bits, keys, seed, tag, variant, cell).drop(f"{out}_sigma", f"{out}_seen")


def opened_column(df: DataFrame, name: str, out: str, keys: Keys) -> DataFrame:
    work = df.withColumn(out, shares.open_(Shared.of(name)))
    ok: Column = shares.mac_ok(Shared.of(name), F.col(out), keys)
    return work.withColumn(f"{out}_ok", ok)
