"""False-positive rates of membership filters, as columns and as Python twins."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

MAX_HASHES = 32


def num_hashes(m, n, most: int = MAX_HASHES):
    """ceil(m / n ln 2), from 1 to ``most``."""
    if isinstance(m, Column) or isinstance(n, Column):
        return F.least(F.greatest(F.ceil(m / n * F.lit(math.log(2))), F.lit(1).cast("long")), F.lit(most).cast("long")).cast("int")
    return int(min(max(math.ceil(m / n * math.log(2)), 1), most)) if n else 1


def bloom_fpr(m, n, form: str = "load_aware", most: int = MAX_HASHES):
    """Rate of a Bloom filter of ``m`` bits with ``n`` elements; ``half_full`` is the textbook optimum."""
    h = num_hashes(m, n, most)
    if isinstance(m, Column) or isinstance(n, Column):
        rate = F.pow(F.lit(0.5), h) if form == "half_full" else F.pow(1 - F.exp(-h * n / m), h)
        return F.when(m <= 0, F.lit(1.0)).when(n <= 0, F.lit(0.0)).otherwise(rate)
    if m <= 0:
        return 1.0
    return 0.0 if n <= 0 else 0.5**h if form == "half_full" else (1 - math.exp(-h * n / m)) ** h


@dataclass(frozen=True)
class AmqSpec:
    """A membership filter kind: its rate from bits per element."""

    name: str
    fpr: Callable[[float], float]


def _blocked(b: float, block: int = 512) -> float:
    """Bloom filter in blocks of one cache line: the rate averaged over the Poisson load of a block."""
    load, h = block / b, max(1, round(b * math.log(2)))
    total = 0.0
    for i in range(int(load + 12 * math.sqrt(load) + 12)):
        weight = math.exp(i * math.log(load) - load - math.lgamma(i + 1))
        total += weight * (1 - (1 - 1 / block) ** (h * i)) ** h
    return min(1.0, total)


KINDS = {
    "bloom": AmqSpec("bloom", lambda b: bloom_fpr(b, 1)),
    "blocked_bloom": AmqSpec("blocked_bloom", _blocked),
    "xor": AmqSpec("xor", lambda b: min(1.0, 2 ** -(b / 1.23))),
    "cuckoo": AmqSpec("cuckoo", lambda b: min(1.0, 8 * 2 ** -(0.95 * b))),
    "quotient": AmqSpec("quotient", lambda b: min(1.0, 2 ** -(0.95 * b - 2.125))),
    "ribbon": AmqSpec("ribbon", lambda b: min(1.0, 2 ** -(b / 1.05))),
}


def one_minus_pow(p: Column, n: Column) -> Column:
    """1 - (1-p)^n without loss for small p."""
    return F.when(n <= 0, 0.0).when(p >= 1, 1.0).otherwise(-F.expm1(n * F.log1p(-F.least(p, F.lit(1 - 1e-16)))))


def probe_bin(n: Column) -> Column:
    """Bin i holds the counts from 2^(i-1) to 2^i - 1; bin 0 holds 0."""
    from rangegate.functions.keys import bit_length

    return bit_length(n.cast("long")).cast("int")


def might_hold(words: Column, positions: Column) -> Column:
    """Whether all positions are set in an array of 64-bit words."""
    return F.forall(positions, lambda p: F.getbit(F.get(words, F.shiftrightunsigned(p, 6).cast("int")), p.bitwiseAND(F.lit(63).cast("long")).cast("int")) == 1)


def sample_bound(n: int, deviation: float, p: float = 0.1) -> float:
    """Bound on the chance that an estimated rate is off by more than ``deviation``."""
    x = n * deviation * deviation
    return min(2 * math.exp(-2 * x), math.exp(-x / (2 * p)) + math.exp(-x / (3 * p)))


def required_sample(deviation: float, chance: float, p: float = 0.1) -> int:
    low, high = 1, 1
    while sample_bound(high, deviation, p) > chance:
        high *= 2
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if sample_bound(mid, deviation, p) <= chance else (mid + 1, high)
    return low


def min_bits_per_key(width: int, error: float) -> float:
    """Order of the space any range-emptiness filter needs for queries of one width."""
    return math.log2(width) + math.log2(1 / error)
