"""Expected false-positive rate of one query under a design; all in closed form."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from rangegate.functions.amq import one_minus_pow
from rangegate.functions.keys import KeySpace


def fpr_single(near: Column, span: Column, length: Column, p: Column) -> Column:
    """Certain once the query shares a whole prefix with a key, else one chance a region."""
    return F.when(near >= length, 1.0).otherwise(one_minus_pow(p, span))


def end_regions(space: KeySpace, l1: Column, l2: Column) -> dict[str, Column]:
    """How many l2 regions of each end lie under the query's first and last l1 region, and which end meets a key.

    A query inside one l1 region has one end.
    """
    d = (l2 - l1).cast("int")
    a0, a1, first, last = space.prefix("lo", l1), space.prefix("hi", l1), space.prefix("lo", l2), space.prefix("hi", l2)
    left = lambda x: F.call_function("shiftleft", x, d)
    return {
        "nl": F.least(last, left(a0 + 1) - 1) - first + 1,
        "nr": last - F.greatest(first, left(a1)) + 1,
        "hl": F.when(a0 == a1, F.col("near") >= l1).otherwise(F.col("lcp_l") >= l1),
        "hr": (a0 != a1) & (F.col("lcp_r") >= l1),
    }


def probes(space: KeySpace, l1: Column, l2: Column) -> Column:
    """Bloom probes of an empty query under a trie of depth l1 and prefixes of length l2."""
    e = end_regions(space, l1, l2)
    return F.when(e["hl"], e["nl"]).otherwise(0) + F.when(e["hr"], e["nr"]).otherwise(0)


def fpr_hybrid(space: KeySpace, l1: Column, l2: Column, p: Column, mode: str = "exact") -> Column:
    n = probes(space, l1, l2)
    some = one_minus_pow(p, n) if mode == "exact" else F.least(F.lit(1.0), n * p)
    return F.when(l2 == 0, F.when(F.col("near") >= l1, 1.0).otherwise(0.0)).when(F.col("near") >= l2, 1.0).otherwise(some)


def fpr_dual(space: KeySpace, l1: Column, l2: Column, p1: Column, p2: Column, form: str = "product") -> Column:
    """Two Bloom filters: every first-level region that says yes is expanded at the second length.

    Regions fully inside an empty query hold no key, so their number of false yes answers is binomial and the sum over
    it collapses to a power; ``sum`` adds the terms one by one and serves to verify that. ``printed`` is the published
    form as it stands, with sums where chances multiply and without the negatives of the first filter, clipped to 0 .. 1;
    it is kept to compare only.
    """
    e = end_regions(space, l1, l2)
    d = (l2 - l1).cast("int")
    size = F.call_function("shiftleft", F.lit(1).cast("long"), d)
    one = space.prefix("lo", l1) == space.prefix("hi", l1)
    cut_l, cut_r = e["nl"] < size, ~one & (e["nr"] < size)
    cut_l = cut_l | (one & (e["nl"] < size))
    full = space.span("lo", "hi", l1) - F.when(cut_l, 1).otherwise(0) - F.when(cut_r, 1).otherwise(0)
    keep = lambda n: 1 - one_minus_pow(p2, n)
    end = lambda hit, n: F.when(hit, keep(n)).otherwise((1 - p1) + p1 * keep(n))
    neg_l = F.when(cut_l, end(e["hl"], e["nl"])).otherwise(1.0)
    neg_r = F.when(cut_r, end(e["hr"], e["nr"])).otherwise(1.0)
    inner = 1 - one_minus_pow(p1 * one_minus_pow(p2, size), full)
    if form == "sum":
        inner = _interior(F.greatest(full, F.lit(0)).cast("long"), p1, p2, d)
    total = 1 - neg_l * neg_r * inner
    if form == "printed":
        cut_r = e["nr"] < size
        once = lambda cut, known, n: F.when(cut, F.when(known, 1.0).otherwise(p1) * keep(n)).otherwise(0.0)
        regions = space.span("lo", "hi", l1) - F.when(cut_l, 1).otherwise(0) - F.when(cut_r, 1).otherwise(0)
        inner = 1 - one_minus_pow(p1 * one_minus_pow(p2, size), F.greatest(regions, F.lit(0)))
        left, right = once(cut_l, e["hl"] & ~one, e["nl"]), once(cut_r, e["hr"] | (one & e["hl"]), e["nr"])
        total = F.least(F.lit(1.0), F.greatest(F.lit(0.0), 1 - left - right - inner))
    return F.when(F.col("near") >= l2, 1.0).otherwise(total)


def binomial_pmf(n: int, i: int, p: float) -> float:
    if p <= 0 or p >= 1:
        return float(i == (0 if p <= 0 else n))
    return math.exp(math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p))


def interior_sum(n: int, p1: float, p2: float, d: int) -> float:
    """The explicit binomial sum that the closed form replaces."""
    return sum(binomial_pmf(n, i, p1) * (1 - p2) ** (i << d) for i in range(n + 1))


def _interior(n: Column, p1: Column, p2: Column, d: Column) -> Column:
    @F.pandas_udf("double")
    def total(n: pd.Series, p1: pd.Series, p2: pd.Series, d: pd.Series) -> pd.Series:
        return pd.Series([interior_sum(int(a), b, c, int(e)) for a, b, c, e in zip(n, p1, p2, d, strict=True)])

    return total(n, p1, p2, d)


def max_probes(l1: int, l2: int) -> int:
    """Bound on second-level probes of an empty query that meets no key at length l2."""
    return (1 << (l2 - l1 + 1)) - 2
