"""Canonical text of elements, and the keyed hash that places an element in a sketch."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .params import SketchParams


def canon(col: Column, kind: T.DataType | None = None) -> Column:
    """Text of an element; structs and arrays are framed by lengths, so ('a','bc') differs from ('ab','c')."""
    if isinstance(kind, T.MapType):
        raise TypeError("maps have no canonical order; pass sorted entries")
    if isinstance(kind, T.StructType):
        return F.concat(*[_framed(canon(col[f.name], f.dataType)) for f in kind.fields])
    if isinstance(kind, T.ArrayType):
        return F.array_join(F.transform(col, lambda x: _framed(canon(x, kind.elementType))), "")
    if isinstance(kind, T.BinaryType):
        return F.hex(col)
    return col.cast("string")


def _framed(text: Column) -> Column:
    return F.concat(F.coalesce(F.length(text).cast("string"), F.lit("-")), F.lit(":"), F.coalesce(text, F.lit("")))


def hash60(col: Column, key: str, algo: str = "md5") -> Column:
    """A non-negative 60-bit integer; ``md5`` and ``sha2`` are the same in any engine, ``xx64`` is the fast one."""
    if algo == "xx64":
        return F.xxhash64(F.lit(key), col).bitwiseAND(F.lit((1 << 60) - 1))
    text = F.concat(F.lit(key + "|"), col)
    digest = F.md5(text) if algo == "md5" else F.sha2(text, 256)
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("bigint")


def uniform(col: Column, key: str) -> Column:
    """A reproducible uniform in [0, 1)."""
    return hash60(col, key) / F.lit(float(1 << 60))


def bucket(h: Column, p: SketchParams) -> Column:
    return h.bitwiseAND(F.lit(p.m - 1)).cast("int")


def rank_of(high: Column, w: int) -> Column:
    """Trailing zeros of a string of ``w - 1`` bits; all zeros give ``w - 1``."""
    zeros = F.bit_count(high.bitwiseAND(-high) - F.lit(1))
    return F.when(high == 0, F.lit(w - 1)).otherwise(zeros).cast("int")


def rank(h: Column, p: SketchParams) -> Column:
    return rank_of(F.shiftrightunsigned(h, p.r).bitwiseAND(F.lit((1 << (p.w - 1)) - 1)), p.w)


def hash_sql(text: str, key: str) -> str:
    return f"('0x' || substr(md5('{key}|' || {text}), 1, 15))::BIGINT"


def rank_sql(high: str, w: int) -> str:
    return f"(CASE WHEN ({high}) = 0 THEN {w - 1} ELSE bit_count((({high}) & -({high})) - 1) END)::INT"


def place_sql(text: str, p: SketchParams, key: str | None = None) -> tuple[str, str]:
    h = hash_sql(text, p.key if key is None else key)
    return f"({h} & {p.m - 1})::INT", rank_sql(f"({h} >> {p.r}) & {(1 << (p.w - 1)) - 1}", p.w)
