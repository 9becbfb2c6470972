"""Arithmetic hash family that Spark, DuckDB and numpy compute alike, and a 64-bit one for filters beyond its range."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = (1 << 31) - 1
PART = 1 << 15


def _seeded(seed: int) -> tuple[int, int, int]:
    return (48271 * (2 * seed + 1)) % P, (69621 * (2 * seed + 3)) % P, (12345 + 7919 * seed) % P


def mix(seed: int, x: Column) -> Column:
    """31-bit hash of a non-negative long."""
    a, b, c = (F.lit(v).cast("long") for v in _seeded(seed))
    p = F.lit(P).cast("long")
    t = ((a * (x % p)) % p + (b * (F.call_function("div", x, p) % p)) % p + c) % p
    t = ((t * t) % p + c) % p
    t = ((a * t) % p + b) % p
    return ((t * t) % p + (t * c) % p + a) % p


def _rest(x: np.ndarray) -> np.ndarray:
    """x mod P of non-negative longs, without a division, as P is 2^31 - 1."""
    x = (x & P) + (x >> 31)
    x = (x & P) + (x >> 31)
    return x - P * (x >= P)


def _mixed(seed: int, x: np.ndarray) -> np.ndarray:
    a, b, c = _seeded(seed)
    if len(x) and x.min() < 0:
        quotient, rest = np.divmod(x, P)
        quotient %= P
    else:
        high = x >> 31
        rest = high + (x & P)
        more, rest = rest >> 31, (rest & P) + (rest >> 31)
        over = rest >= P
        quotient, rest = _rest(high + more + over), rest - P * over
    t = _rest(_rest(a * rest) + _rest(b * quotient) + c)
    t = _rest(_rest(t * t) + c)
    t = _rest(_rest(a * t) + b)
    return _rest(_rest(t * t) + _rest(t * c) + a)


def mix_numpy(seed: int, x: np.ndarray) -> np.ndarray:
    """``mix`` of an array, in parts that fit a core's cache."""
    flat = np.ravel(x)
    out = np.empty(len(flat), np.int64)
    for at in range(0, len(flat), PART):
        out[at : at + PART] = _mixed(seed, flat[at : at + PART].astype(np.int64))
    return out.reshape(np.shape(x))


def wide(high: int, low: int, x: Column) -> Column:
    """62-bit hash from two of 31 bits."""
    return F.shiftleft(mix(high, x), 31).bitwiseOR(mix(low, x))


def bloom_positions(x: Column, m: Column, h: int | Column) -> Column:
    """Array of the bit positions of an element in a filter of ``m`` bits, by double hashing."""
    first, step = mix(101, x), 1 + mix(102, x) % F.greatest(m - 1, F.lit(1))
    return F.transform(F.sequence(F.lit(0), (F.lit(h) if isinstance(h, int) else h) - 1), lambda i: (first + i.cast("long") * step) % m)


def mix64(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """64-bit hash of longs; a bijection for each seed."""
    with np.errstate(over="ignore"):
        x = x.astype(np.uint64) + np.uint64((2 * seed + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def hash_pair(x: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Start and step of the double hashing of a filter of ``m`` bits; beyond 31 bits the arithmetic family is too narrow."""
    if m <= P:
        return mix_numpy(101, x), 1 + mix_numpy(102, x) % max(m - 1, 1)
    first, step = ((mix64(x, s) >> np.uint64(2)).astype(np.int64) for s in (101, 102))
    return first % m, 1 + step % (m - 1)


def raw_pair(x: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """The hashes that start and step come from; the same for all filters of up to 2^31 bits, and for all larger ones."""
    if m <= P:
        return mix_numpy(101, x).astype(np.uint32), mix_numpy(102, x).astype(np.uint32)
    return tuple((mix64(x, s) >> np.uint64(2)).astype(np.int64) for s in (101, 102))


def start_and_step(first: np.ndarray, step: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Both from ``raw_pair``, below ``m`` (a step in a filter of one bit is 1)."""
    size, most = (np.uint32(x) if m <= P else np.int64(x) for x in (m, max(m - 1, 1)))
    return first - first // size * size, step - step // most * most + first.dtype.type(1)


def next_place(at: np.ndarray, step: np.ndarray, m: int) -> np.ndarray:
    """(at + step) mod m; a difference below zero wraps around to a number above all places."""
    at = (at + step).view(np.uint32 if m <= P else np.uint64)
    return np.minimum(at, at - at.dtype.type(m)).view(step.dtype)


def places(first: np.ndarray, step: np.ndarray, m: int, h: int) -> Iterator[np.ndarray]:
    """The ``h`` places of each element, one array a hash."""
    at, step = start_and_step(first, step, m)
    for i in range(h):
        at = next_place(at, step, m) if i else at
        yield at
