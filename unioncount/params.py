"""Parameters of sketches and of the protocol."""

from __future__ import annotations

import math
from dataclasses import dataclass

#: Prime of the default field: products of two reduced values fit DECIMAL(38, 0).
P61 = (1 << 61) - 1
#: Prime of 40 + 32 bits: statistic and noise fit 32 bits, 40 more keep masked openings from telling anything.
P72 = (1 << 72) - 93


@dataclass(frozen=True)
class SketchParams:
    """``m`` arrays (a power of two) of ``w`` bits; ``key`` is the holders' secret and never printed."""

    m: int = 64
    w: int = 12
    key: str = "k"
    hash: str = "md5"

    def __post_init__(self) -> None:
        if self.m < 1 or self.m & (self.m - 1):
            raise ValueError("m must be a power of two")
        if not 2 <= self.w <= 60 - self.r:
            raise ValueError("w must lie between 2 and 60 - log2 m")

    @property
    def r(self) -> int:
        return self.m.bit_length() - 1

    def __repr__(self) -> str:
        return f"SketchParams(m={self.m}, w={self.w}, hash={self.hash})"


#: Small parameters whose SQL twins are cheap, and those of the accuracy study.
ORACLE = SketchParams()
STUDY_M, STUDY_EPS, STUDY_DELTA, STUDY_EPS_D = 4096, 0.1, 1e-12, 0.012


def choose_width(kind: str, n_max: float, m: int) -> int:
    """Bits of an array for up to ``n_max`` elements: first-zero arrays see all elements, the others a share 1/m."""
    load = n_max if kind == "fz" else n_max / m
    return max(2, min(60 - (m.bit_length() - 1), math.ceil(math.log2(max(load, 2**-5)) + 6)))


def sensitivity(kind: str, m: int, w: int) -> float:
    """How far one element moves the released statistic: zero bits 1, first-zero sum w per array, mean rank (w-1)/m."""
    return {"zc": 1.0, "fz": float(w * m), "mr_mean": (w - 1) / m}[kind]


@dataclass(frozen=True)
class ProtocolConfig:
    """``c`` computing parties; ``sigma`` of each holder's noise; ``seed`` of the randomness; ``prime`` of the field.

    A given seed makes a run reproducible, for tests and oracles.  A release takes ``params.fresh_seed()``, a secret from
    the operating system, and draws of ``noise.os_draws``.
    """

    sketch: SketchParams = ORACLE
    c: int = 3
    sigma: float = 2.0
    seed: str = "s"
    prime: int = P61

    def __repr__(self) -> str:
        return f"ProtocolConfig({self.sketch}, c={self.c}, sigma={self.sigma}, prime of {self.prime.bit_length()} bits)"


def fresh_seed() -> str:
    """256 secret bits of the operating system: shares, masks and MAC keys are then SHA-256 values under them, so that a
    task that runs again deals the same shares."""
    import secrets

    return FRESH + secrets.token_hex(32)


#: How seeds from the operating system begin.
FRESH = "os:"
