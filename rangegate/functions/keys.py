"""Order-preserving key codes of k <= 63 bits (non-negative longs) and their prefixes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


@dataclass(frozen=True)
class KeySpace:
    bits: int

    def prefix(self, code, length: int | Column) -> Column:
        """Leading ``length`` bits; none of them is 0."""
        if isinstance(length, int):
            return F.lit(0).cast("long") if length == 0 else F.shiftrightunsigned(_c(code), self.bits - length)
        shift = F.lit(self.bits) - length
        return F.when(length == 0, F.lit(0).cast("long")).otherwise(F.call_function("shiftrightunsigned", _c(code), shift.cast("int")))

    def prefix_range(self, prefix, length: int) -> tuple[Column, Column]:
        """Smallest and largest code under a prefix."""
        low = F.shiftleft(_c(prefix), self.bits - length)
        return low, low + F.lit((1 << (self.bits - length)) - 1)

    def span(self, lo, hi, length) -> Column:
        """Number of prefixes that cover [lo, hi]."""
        return self.prefix(hi, length) - self.prefix(lo, length) + 1

    def lcp(self, a, b) -> Column:
        """Length of the common prefix of two codes."""
        return (F.lit(self.bits) - bit_length(_c(a).bitwiseXOR(_c(b)))).cast("int")

    def clip_add(self, code, offset) -> Column:
        """code + offset, at most the largest code."""
        top = F.lit((1 << self.bits) - 1)
        return F.least(_c(code), top - _c(offset)) + _c(offset)


def bit_length(x: Column) -> Column:
    """Bits up to the highest one that is set."""
    for step in (1, 2, 4, 8, 16, 32):
        x = x.bitwiseOR(F.shiftrightunsigned(x, step))
    return F.bit_count(x)


def bit_length_numpy(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64)
    for step in (1, 2, 4, 8, 16, 32):
        x = x | (x >> np.uint64(step))
    return np.bitwise_count(x).astype(np.int64)


def unsigned_code(x) -> Column:
    """Signed long in the order of the 64-bit pattern read as unsigned; longs then compare and sort as unsigned do."""
    return _c(x).bitwiseXOR(F.lit(-(1 << 63)))


def double_code(x) -> Column:
    """Long in the order of a double: bits of a positive one, those of a negative one turned; -0.0 counts as 0.0."""

    @F.pandas_udf("long")
    def code(values: pd.Series) -> pd.Series:
        bits = (values.to_numpy(np.float64) + 0.0).view(np.int64)
        return pd.Series(np.where(bits < 0, bits ^ np.int64(0x7FFFFFFFFFFFFFFF), bits), dtype="int64")

    return F.when(_c(x).isNotNull(), code(F.coalesce(_c(x), F.lit(0.0))))


def dyadic_cover(lo, hi, bits: int) -> Column:
    """Array of (level, block): the fewest aligned blocks of 2^level codes that make up [lo, hi].

    A block belongs to the cover if it lies inside and the block of twice its size around it does not.
    """

    def at(j: int) -> Column:
        first, after = F.shiftright(_c(lo) + F.lit((1 << j) - 1), j), F.shiftright(_c(hi) + 1, j)
        one = lambda use, block: F.when(use, F.array(F.struct(F.lit(j).alias("level"), block.alias("block")))).otherwise(F.array())
        odd = first.bitwiseAND(F.lit(1).cast("long")) == 1
        left = (first < after) & odd
        right = (after.bitwiseAND(F.lit(1).cast("long")) == 1) & (first < after) & ~(odd & (first == after - 1))
        return F.concat(one(left, first), one(right, after - 1))

    return F.concat(*[at(j) for j in range(bits + 1)])


def unsigned_less(a, b) -> Column:
    """a < b of 64-bit patterns read as unsigned."""
    low = F.lit(-(1 << 63))
    return _c(a).bitwiseXOR(low) < _c(b).bitwiseXOR(low)


def signed_code(x, bits: int) -> Column:
    """Order-preserving code of a signed integer of ``bits`` bits."""
    return _c(x) + F.lit(1 << (bits - 1))


def timestamp_code(ts, origin_micros: int) -> Column:
    return F.unix_micros(_c(ts).cast("timestamp")) - F.lit(origin_micros)


def cents(x) -> Column:
    return F.round(_c(x) * 100).cast("long")


def composite(*parts: tuple) -> Column:
    """Bit-packed columns (column, bits), the first one highest."""
    out = F.lit(0).cast("long")
    for column, bits in parts:
        out = F.shiftleft(out, bits).bitwiseOR(_c(column).cast("long"))
    return out


def zorder(a, b, bits: int) -> Column:
    """Interleaved bits of two codes, ``a`` first."""
    out = F.lit(0).cast("long")
    for i in range(bits):
        for j, x in ((1, a), (0, b)):
            out = out.bitwiseOR(F.shiftleft(F.shiftrightunsigned(_c(x), i).bitwiseAND(F.lit(1).cast("long")), 2 * i + j))
    return out
