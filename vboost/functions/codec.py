"""Fixed-point encoding, bit budgets, packing of gradient with hessian, compression, and multi-class packing.

A packed integer holds the offset gradient above the hessian. Adding packed integers adds both fields; the budget is
wide enough for the sum over all rows, so no field carries into the next.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Two 32-bit limbs are summed as BIGINT: exact for up to 2^31 rows of a cell; beyond that ANSI mode raises.
LIMB = 1 << 32
#: Bits of a high limb at most, so that doubles hold it whole.
HIGH_BITS = 53


@dataclass(frozen=True)
class Budget:
    """Bits of the fields for n rows at r fractional bits; g_off makes gradients non-negative."""

    n: int
    r: int = 53
    g_max: float = 1.0
    g_off: float = 1.0
    h_max: float = 1.0
    iota: int = 1023
    rounding: str = "floor"

    @property
    def b_g(self) -> int:
        return int(self.n * (int(self.g_off * 2**self.r) + int(self.g_max * 2**self.r))).bit_length()

    @property
    def b_h(self) -> int:
        return int(self.n * int(self.h_max * 2**self.r)).bit_length()

    @property
    def b_gh(self) -> int:
        return self.b_g + self.b_h

    @property
    def slots(self) -> int:
        """Packed integers that one plaintext holds: for compression, and classes of a ciphertext."""
        return self.iota // self.b_gh

    def n_k(self, classes: int) -> int:
        return -(-classes // self.slots)

    def members(self, classes: int = 1) -> int:
        """Split infos that one package holds: of one cipher each, so of as many classes as fit."""
        return self.iota // (classes * self.b_gh)

    @property
    def offset(self) -> int:
        return int(self.g_off * 2**self.r)

    def amplified(self, factor: float) -> "Budget":
        """The budget where sampling multiplies gradients and hessians."""
        return replace(self, g_max=self.g_max * factor, g_off=self.g_off * factor, h_max=self.h_max * factor)

    def fixed(self, x: float) -> int:
        """x at r fractional bits: the same integer as the limbs of the native sums."""
        return math.floor((x + 0.5 / 2.0**self.r if self.rounding == "round" else x) * 2.0**self.r)


def limbs(x: Column, r: int, rounding: str = "floor") -> tuple[Column, Column]:
    """High and low limb of floor(x * 2^r), for BIGINT sums inside code generation.

    Every step is exact on doubles. A value beyond 2^(HIGH_BITS + 32 - r), or NaN, raises.
    """
    if rounding == "round":
        x = x + 0.5 / 2.0**r
    scaled = x * float(2.0 ** (r - 32))
    high = F.floor(scaled).cast("bigint")
    low = F.floor((scaled - F.floor(scaled)) * float(LIMB)).cast("bigint")
    wrong = F.raise_error(F.lit("a gradient or hessian exceeds the fixed-point range")).cast("bigint")
    return F.when(x.isNull() | (F.abs(scaled) < float(1 << HIGH_BITS)), high).otherwise(wrong), low


def unlimb(high: Column, low: Column) -> Column:
    return (high.cast("decimal(20,0)") * F.lit(LIMB).cast("decimal(11,0)") + low.cast("decimal(20,0)")).cast("decimal(38,0)")


def real(x: Column, r: int) -> Column:
    return x.cast("double") / float(2**r)


def pack(g: float, h: float, b: Budget) -> int:
    """The offset gradient above the hessian. Values beyond the declared bounds raise: their sums would not fit."""
    if not (-b.g_off <= g <= b.g_max and 0 <= h <= b.h_max):
        raise OverflowError(f"gradient {g} or hessian {h} beyond the declared bounds {b.g_max}, {b.h_max}")
    return (b.fixed(g) + b.offset << b.b_h) + b.fixed(h)


def fields(g: np.ndarray, h: np.ndarray, b: Budget) -> tuple[np.ndarray, np.ndarray] | None:
    """The two fields that `pack` joins, of arrays, and its error; None where 64 bits do not hold them."""
    if max(b.g_max, b.g_off, b.h_max) * 2.0**b.r >= 2.0**61:
        return None
    wrong = ~((-b.g_off <= g) & (g <= b.g_max) & (0 <= h) & (h <= b.h_max))
    if wrong.any():
        k = np.argmax(wrong.ravel())
        pack(float(g.ravel()[k]), float(h.ravel()[k]), b)
    half = 0.5 / 2.0**b.r if b.rounding == "round" else 0.0
    fixed = lambda x: np.floor((x + half) * 2.0**b.r).astype(np.int64)
    return fixed(g) + b.offset, fixed(h)


def apart(g: float, h: float, b: Budget) -> list[int]:
    """Two integers, without packing."""
    both = pack(g, h, b)
    return [both >> b.b_h, both & ((1 << b.b_h) - 1)]


def unpack(total: int, count: int, b: Budget) -> tuple[int, int]:
    """Fixed-point sums of g and h from a sum of `count` packed integers."""
    return (total >> b.b_h) - count * b.offset, total & ((1 << b.b_h) - 1)


def compress(values: list[int], b: Budget, classes: int = 1) -> int:
    """Horner fold: the first member ends in the highest slot. A member holds `classes` packed integers."""
    if len(values) * classes > b.slots:
        raise ValueError(f"{len(values)} members of {classes} do not fit {b.slots} slots")
    acc = 0
    for v in values:
        acc = (acc << classes * b.b_gh) + v
    return acc


def decompress(package: int, members: int, b: Budget, classes: int = 1) -> list[int]:
    wide = classes * b.b_gh
    mask, out = (1 << wide) - 1, []
    for _ in range(members):
        out.append(package & mask)
        package >>= wide
    return out[::-1]


def pack_mo(g: list[float], h: list[float], b: Budget) -> list[int]:
    """n_k integers; classes in order, the first class of an integer in its highest slot."""
    each = [pack(x, y, b) for x, y in zip(g, h)]
    return [compress(each[i : i + b.slots], b) for i in range(0, len(each), b.slots)]


def unpack_mo(totals: list[int], count: int, classes: int, b: Budget) -> list[tuple[int, int]]:
    """Fixed-point sums of each class; the last integer may hold fewer classes."""
    out: list[tuple[int, int]] = []
    for t in totals:
        out += [unpack(v, count, b) for v in decompress(t, min(b.slots, classes - len(out)), b)]
    return out
