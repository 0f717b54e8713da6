"""Authenticated additive shares: a shared value is one row with an array of values and one of MACs, a slot a party.

The shares, keys, masks and opened values are those of the protocol; what is simulated is that the parties do not trust
each other, since one cluster holds all slots.  Keeping the slots of a cell in one row makes every linear step and every
opening a projection: no step of the protocol but the sum over holders shuffles.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import field
from .hashing import hash60
from .params import FRESH


@dataclass(frozen=True, repr=False)
class Keys:
    """MAC key shares of the parties; their sum is the key, which no party knows."""

    shares: tuple[int, ...]

    @property
    def total(self) -> int:
        return sum(self.shares) % field.modulus()

    @staticmethod
    def agree(c: int, seed: str) -> Keys:
        import hashlib

        return Keys(tuple(int(hashlib.sha256(f"{seed}|key|{j}".encode()).hexdigest(), 16) % field.modulus() for j in range(c)))

    def __repr__(self) -> str:
        return f"Keys of {len(self.shares)} parties"


@dataclass(frozen=True)
class Shared:
    """Columns ``val`` and ``mac``, arrays with a slot for each party."""

    val: Column
    mac: Column

    @staticmethod
    def of(name: str) -> Shared:
        return Shared(F.col(name)["val"], F.col(name)["mac"])

    def column(self) -> Column:
        return F.struct(self.val.alias("val"), self.mac.alias("mac"))


def seeded(cell: Column, seed: str, tag: str) -> Column:
    """A uniform field element from 120 bits that depends on the seed, the tag and the cell alone."""
    return field.reduce_(random_bits(cell, seed, tag))


def random_bits(cell: Column, seed: str, tag: str) -> Column:
    """A uniform number of 120 bits: reproducible under a given seed, unguessable under one of the operating system."""
    algo = "sha2" if seed.startswith(FRESH) else "md5"
    half = lambda k: hash60(cell.cast("string"), f"{seed}|{tag}|{k}", algo).cast("decimal(19,0)")
    return half(0) * F.lit(1 << 60).cast("decimal(19,0)") + half(1)


def _split(value: Column, cell: Column, c: int, seed: str, tag: str) -> Column:
    parts = [seeded(cell, seed, f"{tag}|{j}") for j in range(c - 1)]
    rest = value
    for x in parts:
        rest = rest - x
    return F.array(*parts, field.reduce_(rest))


def deal(value: Column, cell: Column, keys: Keys, seed: str, tag: str) -> Shared:
    """Shares of a reduced value and of its MAC (what the offline phase hands out)."""
    c = len(keys.shares)
    return Shared(_split(value, cell, c, seed, tag + "v"), _split(field.mul(value, field.constant(keys.total)), cell, c, seed, tag + "m"))


def deal_list(values: Column, cell: Column, keys: Keys, seed: str, tag: str) -> Column:
    """Shares of a list of reduced values as ``array<struct<val, mac>>``, one entry a value, in an expression whose size
    does not depend on the number of values."""
    c = len(keys.shares)
    key = field.constant(keys.total)

    def split(x: Column, i: Column, kind: str) -> Column:
        name = lambda j: F.concat_ws("|", cell.cast("string"), i.cast("string"), j.cast("string"))
        parts = F.transform(F.sequence(F.lit(0), F.lit(c - 2)), lambda j: seeded(name(j), seed, tag + kind))
        return F.transform(F.array(parts), lambda p: F.concat(p, F.array(field.reduce_(F.aggregate(p, x, lambda acc, s: (acc - s).cast("decimal(38,0)"))))))[0]

    return F.transform(values, lambda x, i: F.struct(split(x, i, "v").alias("val"), split(field.mul(x, key), i, "m").alias("mac")))


def at(items: Column, i: Column | int) -> Shared:
    """Entry ``i`` of a list of shared values."""
    return Shared(items[i]["val"], items[i]["mac"])


def combine(items: Column, factors: Column, c: int) -> Shared:
    """Sum of the shared values of a list, each times its public factor (reduced); party by party."""
    pairs = F.zip_with(items, factors, lambda s, k: F.struct(s.alias("s"), k.alias("k")))
    zero = F.transform(F.sequence(F.lit(1), F.lit(c)), lambda _: field.constant(0))
    total = lambda part: F.aggregate(pairs, zero, lambda acc, q: F.zip_with(acc, F.transform(q["s"][part], lambda v: field.mul(v, q["k"])), lambda a, b: field.add(a, b)))
    return Shared(total("val"), total("mac"))


def add(x: Shared, y: Shared) -> Shared:
    both = lambda a, b: F.zip_with(a, b, lambda s, t: field.add(s, t))
    return Shared(both(x.val, y.val), both(x.mac, y.mac))


def scale(x: Shared, k: Column) -> Shared:
    by = lambda a: F.transform(a, lambda s: field.mul(s, k))
    return Shared(by(x.val), by(x.mac))


def add_public(x: Shared, k: Column, keys: Keys) -> Shared:
    """Adds a reduced public value: the first party moves its share, every party its MAC by its share of the key."""
    deltas = F.array(*[field.constant(d) for d in keys.shares])
    val = F.transform(x.val, lambda s, i: F.when(i == 0, field.add(s, k)).otherwise(s))
    return Shared(val, F.zip_with(x.mac, deltas, lambda s, d: field.add(s, field.mul(d, k))))


def open_(x: Shared) -> Column:
    """The value that all parties see when they reveal their shares."""
    return field.reduce_(F.aggregate(x.val, field.constant(0), lambda acc, s: (acc + s).cast("decimal(38,0)")))


def mac_ok(x: Shared, opened: Column, keys: Keys) -> Column:
    """Whether the checks of all parties cancel; any altered share, MAC or key makes them not."""
    return cancels(residuals(x, opened, keys))


def share_input(value: Column, cell: Column, keys: Keys, seed: str, tag: str) -> Shared:
    """A holder's value: a random mask is opened to the holder alone, who broadcasts the difference; cells use a mask once."""
    mask_value, mask = deal_mask(cell, keys, seed, tag)
    return add_public(mask, field.sub(value, mask_value), keys)


def deal_mask(cell: Column, keys: Keys, seed: str, tag: str) -> tuple[Column, Shared]:
    """A holder's mask, which that holder alone may see, and its shares."""
    value = seeded(cell, seed, tag + "|mask")
    return value, deal(value, cell, keys, seed, tag + "|maskshare")


def residuals(x: Shared, opened: Column, keys: Keys) -> Column:
    """What each party commits to after an opening: its MAC less the opened value times its share of the key."""
    deltas = F.array(*[field.constant(d) for d in keys.shares])
    return F.zip_with(x.mac, deltas, lambda s, d: field.sub(s, field.mul(d, opened)))


def batched(openings: list[tuple[Shared, Column]], cell: Column, keys: Keys, seed: str, tag: str) -> Column:
    """One residual a party for several openings: a random combination, so that errors cannot cancel but by chance."""

    def weighed(x: Shared, opened: Column, weight: Column) -> Column:
        return F.transform(F.array(weight), lambda k: F.transform(residuals(x, opened, keys), lambda s: field.mul(s, k)))[0]

    parts = [weighed(x, opened, seeded(cell, seed, f"{tag}|{i}")) for i, (x, opened) in enumerate(openings)]
    return reduce(lambda x, y: F.zip_with(x, y, lambda a, b: field.add(a, b)), parts)


def cancels(parties: Column) -> Column:
    """Whether the residuals of all parties add up to nothing."""
    return field.reduce_(F.aggregate(parties, field.constant(0), lambda acc, s: (acc + s).cast("decimal(38,0)"))) == 0


def multiply_dealt(x: Shared, y: Shared, u: Shared, v: Shared, uv: Shared, keys: Keys) -> tuple[Shared, list[tuple[Shared, Column]]]:
    """Product of two shared values by a dealt triple, with its two openings, which are uniform."""
    dx, dy = add(x, scale(u, field.constant(-1))), add(y, scale(v, field.constant(-1)))
    a, b = open_(dx), open_(dy)
    return add_public(add(add(uv, scale(v, a)), scale(u, b)), field.mul(a, b), keys), [(dx, a), (dy, b)]


def multiply(x: Shared, y: Shared, cell: Column, keys: Keys, seed: str, tag: str) -> tuple[Shared, list[tuple[Shared, Column]]]:
    """Product by a triple that is dealt here; returns it with the two openings."""
    u, v = seeded(cell, seed, tag + "|u"), seeded(cell, seed, tag + "|v")
    su, sv, suv = deal(u, cell, keys, seed, tag + "|su"), deal(v, cell, keys, seed, tag + "|sv"), deal(field.mul(u, v), cell, keys, seed, tag + "|suv")
    return multiply_dealt(x, y, su, sv, suv, keys)


def share_sum(name: str, c: int) -> Column:
    """Aggregate of the shared column ``name``: party by party, so no message is needed."""
    total = lambda part: F.array(*[field.reduce_(F.sum(F.col(name)[part][j])) for j in range(c)])
    return F.struct(total("val").alias("val"), total("mac").alias("mac"))


def residual_sum(name: str, c: int) -> Column:
    """Aggregate of the parties' residuals."""
    return F.array(*[field.reduce_(F.sum(F.col(name)[j])) for j in range(c)])


def sum_shares(df: DataFrame, by: list[str], name: str, c: int) -> DataFrame:
    """Sum of the shared column ``name`` within ``by``."""
    return df.groupBy(*by).agg(share_sum(name, c).alias(name))


def long_view(df: DataFrame, name: str, cell: str = "cell") -> DataFrame:
    """``cell, cp, val, mac``: a row for each party."""
    pairs = F.arrays_zip(F.col(name)["val"].alias("val"), F.col(name)["mac"].alias("mac"))
    return df.select(cell, F.posexplode(pairs).alias("cp", "s")).select(cell, "cp", F.col("s")["val"].alias("val"), F.col("s")["mac"].alias("mac"))


def tamper(x: Shared, cp: int, part: str = "val", by: int = 1) -> Shared:
    """A copy in which party ``cp`` has altered its share or its MAC."""
    change = lambda a: F.transform(a, lambda s, i: F.when(i == cp, field.add(s, field.constant(by))).otherwise(s))
    return Shared(change(x.val), x.mac) if part == "val" else Shared(x.val, change(x.mac))
