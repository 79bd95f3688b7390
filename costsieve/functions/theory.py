"""Closed forms for error rates, owners and the reach of the optimiser."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def bloom_fpr(b: float, k: int) -> float:
    """Rate of a standard filter with b bits per key and k functions."""
    return (1 - math.exp(-k / b)) ** k


def two_round_fpr(f: float, r: float) -> float:
    """Rate of a two-round probe whose bit array passes f and whose table misreads r of the keys."""
    return f + r * f - r * f * f


def two_round_bound(f: float, stored: float, omega: float) -> float:
    return (1 + stored / omega) * f


def _g(x: float) -> float:
    return x / math.expm1(x) if x else 1.0


def owner_prob(b: float, k: int) -> float:
    """Lower estimate of the chance that a set bit has a single owner."""
    return _g(k / b)


def owners_expected(b: float, k: int) -> float:
    return k * _g(k / b)


def p_store(stored: float, omega: float, k: int) -> float:
    """Chance that a subset can be stored after ``stored`` others."""
    return max(0.0, 1 - (k * stored + k) / omega) ** k


def p_swap(n: int, o: int, m: int, k: int, pool: int) -> float:
    """Chance that an owner has a swap that frees the key and breaks none; swaps that break cheaper keys are left out."""
    p = 1 - math.exp(-k * n / m)
    quiet = math.exp(-(k * o / m) * p ** (k - 1))
    q = p + (1 - p) * quiet
    return 1 - (1 - q) ** (pool - k)


def p_optimise(swap: float, store: float) -> float:
    return swap * store


def optimised_lower(t: float, p: float, omega: float, k: int) -> float:
    """Of t collision keys, at least so many are expected to be freed."""
    return max(0.0, t * p * (omega - k * k) / (omega + t * p * k * k))


def fpr_upper(n: int, o: int, m: int, omega: int, k: int, pool: int) -> float:
    f = bloom_fpr(m / n, k)
    return f - optimised_lower(f * o, p_swap(n, o, m, k, pool), omega, k) / o


def xor_fpr(bits: int) -> float:
    return 2.0**-bits


def shard_bytes(n: int, o: int, m: int, pool: int, k: int) -> int:
    """Memory of the shard kernel: positions, hits, owners and the reliance index."""
    return n * (pool + 1) * 8 + o * k * 16 + m * 12


class columns:
    """The same forms over columns. ``x`` are functions times keys over bits."""

    @staticmethod
    def bloom_fpr(x: Column, k: Column) -> Column:
        return F.pow(1 - F.exp(-x), k)

    @staticmethod
    def owner_prob(x: Column) -> Column:
        return x / (F.exp(x) - 1)

    @staticmethod
    def fpr_upper(n: Column, o: Column, m: Column, omega: Column, k: int, pool: int) -> Column:
        p = 1 - F.exp(-k * n / m)
        f = F.pow(p, F.lit(k))
        q = p + (1 - p) * F.exp(-(k * o / m) * F.pow(p, F.lit(k - 1)))
        reach = f * o * (1 - F.pow(1 - q, F.lit(pool - k)))
        return f - F.greatest(F.lit(0.0), reach * (omega - k * k) / (omega + reach * k * k)) / o
