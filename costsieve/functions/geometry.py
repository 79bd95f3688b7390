"""How a space budget is split. All integer arithmetic, so that every engine gets the same sizes."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction


@dataclass(frozen=True)
class Geometry:
    m: int  # bits of the bit array
    omega: int  # cells of the chain table
    alpha: int  # bits of a cell
    pool: int  # hash functions to choose from

    @property
    def total_bits(self) -> int:
        return self.m + self.omega * self.alpha


def pool_size(alpha: int, most: int = 22) -> int:
    """Functions a cell of ``alpha`` bits can name: one bit is the end flag and the index 0 means empty."""
    return min(most, (1 << alpha - 1) - 1)


def split(total_bits: int, delta: float | Fraction = Fraction(1, 4), alpha: int = 4) -> Geometry:
    """``delta`` is the chain table's space over the bit array's."""
    share = Fraction(delta).limit_denominator(1000)
    omega = total_bits * share.numerator // (share.numerator + share.denominator) // alpha
    return Geometry(total_bits - omega * alpha, omega, alpha, pool_size(alpha))


def budget(n: int, bits_per_key: float) -> int:
    """Bits for n keys; bits per key count in hundredths."""
    return n * round(bits_per_key * 100) // 100


def best_k(bits_per_key: float) -> int:
    return max(1, round(bits_per_key * math.log(2)))


def fingerprint_bits(bits_per_key: float, n: int) -> int:
    return max(1, math.floor(bits_per_key / (1.23 + 32 / n)))
