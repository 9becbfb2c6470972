"""Construction of one run's filter in one task: counts, trie memory, query evidence, rates of all designs, build.

A run is bounded by the store (``balanced_runs``), the sample by its queue, so each run is one group and all runs are one
stage: the keys of a run move once, the sample is broadcast behind a check of its size. The DataFrame form of the same
search (``search``) is for inspection and for oracles; both choose the same designs.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from copy import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangegate.functions.amq import bloom_fpr
from rangegate.functions.keys import bit_length_numpy
from rangegate.operators import filters, trie
from rangegate.operators.search import RANK_OVERHEAD

MAX_SAMPLE = 4_000_000
PART = 1 << 15
SPLITS = (0.4, 0.5, 0.6)
STAGES = ("count_keys", "trie_memory", "count_queries", "rates", "build")
RATES = "run_id long, l1 int, l2 int, split double, bloom long, p double, exp_fpr double"
BUILT = filters.FILTER + ", exp_fpr double, " + ", ".join(f"{s}_ms double" for s in STAGES)


def lcp(a: np.ndarray, b: np.ndarray, bits: int) -> np.ndarray:
    return bits - bit_length_numpy(a ^ b)


def key_prefix_counts(codes: np.ndarray, bits: int) -> np.ndarray:
    """Distinct prefixes of each length 0 .. bits, of sorted distinct codes; codes beyond the space begin a prefix of each length."""
    if not len(codes):
        return np.zeros(bits + 1, np.int64)
    fresh = np.zeros(bits + 2, np.int64)
    for at in range(0, len(codes) - 1, PART):
        x = codes[at : at + PART + 1]
        fresh += np.bincount(np.maximum(lcp(x[1:], x[:-1], bits), 0) + 1, minlength=bits + 2)
    return 1 + np.cumsum(fresh[: bits + 1])


def trie_memory(n: np.ndarray, bits: int, rank_overhead: float = RANK_OVERHEAD) -> tuple[np.ndarray, np.ndarray]:
    """Bits and number of dense levels of a uniform trie of each depth 0 .. bits; the cut of least memory."""
    size, dense_levels = np.zeros(bits + 1, np.int64), np.zeros(bits + 1, np.int64)
    for depth in range(1, bits + 1):
        levels = [(s, min(s + 8, depth)) for s in range(0, depth, 8)]
        dense = np.array([float(n[s]) * (2 * 2.0 ** (e - s) + 1) for s, e in levels])
        sparse = np.array([float(n[e]) * (e - s + 2) for s, e in levels])
        cost = np.r_[0, np.cumsum(dense)] + np.r_[np.cumsum(sparse[::-1])[::-1], 0]
        dense_levels[depth] = int(np.argmin(cost))
        size[depth] = int(np.ceil(cost.min() * (1 + rank_overhead)))
    return size, dense_levels


class Evidence:
    """A run's view of the empty queries of a sample: ends, proximity, and what a design makes of them."""

    def __init__(self, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, bits: int):
        at = np.searchsorted(codes, lo)
        after = codes[np.minimum(at, len(codes) - 1)] if len(codes) else lo
        empty = (at == len(codes)) | (after > hi)
        self.bits, self.lo, self.hi = bits, lo[empty], hi[empty]
        at, none = at[empty], np.zeros(int(empty.sum()), np.int64)
        self.left, self.right = none, none
        if len(codes):
            self.left = np.where(at > 0, lcp(self.lo, codes[np.maximum(at - 1, 0)], bits), 0)
            self.right = np.where(at < len(codes), lcp(self.hi, codes[np.minimum(at, len(codes) - 1)], bits), 0)
        self.near = np.maximum(self.left, self.right)

    def __len__(self) -> int:
        return len(self.lo)

    def parts(self) -> Iterator[Evidence]:
        """The queries in parts of bounded size, as the tables of a design have a row a query."""
        for at in range(0, len(self), PART):
            part = copy(self)
            for name in ("lo", "hi", "left", "right", "near"):
                setattr(part, name, getattr(self, name)[at : at + PART])
            yield part

    def ends(self, l1: int, l2: np.ndarray) -> tuple[np.ndarray, ...]:
        """For each query and each l2: regions at the left and right end, and whether the end's l1 region holds a key."""
        k, d = self.bits, l2 - l1
        a0, a1 = self.lo >> (k - l1) if l1 else np.zeros_like(self.lo), self.hi >> (k - l1) if l1 else np.zeros_like(self.hi)
        one = a0 == a1
        first, last = self.lo[:, None] >> (k - l2), self.hi[:, None] >> (k - l2)
        n_left = np.minimum(last, ((a0[:, None] + 1) << d) - 1) - first + 1
        n_right = np.where(one[:, None], 0, last - np.maximum(first, a1[:, None] << d) + 1)
        return n_left, n_right, np.where(one, self.near >= l1, self.left >= l1), ~one & (self.right >= l1), a1 - a0 + 1


def _binned(parts: Iterable[np.ndarray], p: np.ndarray, binned: bool) -> np.ndarray:
    """Sum over queries of 1 - (1-p)^probes for each column; ``binned`` takes the mean of each power-of-two class.

    Probes come in parts of some queries each; classes are those of all.
    """
    if not binned:
        with np.errstate(divide="ignore"):
            return sum(-np.expm1(probes * np.log1p(-np.minimum(p, 1 - 1e-16))[None, :]).sum(axis=0) for probes in parts)
    m = len(p)
    count, total = np.zeros(64 * m, np.int64), np.zeros(64 * m)
    for probes in parts:
        key = (bit_length_numpy(probes) + np.arange(m)[None, :] * 64).ravel()
        count, total = count + np.bincount(key, minlength=64 * m), total + np.bincount(key, probes.ravel().astype(np.float64), 64 * m)
    mean = (total / np.maximum(count, 1)).reshape(m, 64)
    some = np.where((p >= 1)[:, None], (mean > 0).astype(float), -np.expm1(mean * np.log1p(-np.minimum(p, 1 - 1e-16))[:, None]))
    return (count.reshape(m, 64) * some).sum(axis=1)


def hybrid_rates(e: Evidence, n: np.ndarray, tries: np.ndarray, m: int, lengths: Iterable[int], depths: Iterable[int] | None = None, binned: bool = True, form: str = "load_aware") -> list[tuple]:
    """(l1, l2, split, bloom, p, rate) of tries alone (l2 = 0), Bloom filters alone (l1 = 0) and both."""
    out, lengths = [], np.array(sorted(lengths), np.int64)
    for l1 in depths if depths is not None else range(e.bits + 1):
        if tries[l1] > m:
            continue
        bloom = m - int(tries[l1])
        if l1:
            out.append((l1, 0, 0.0, 0, 0.0, float((e.near >= l1).mean())))
        l2 = lengths[lengths > l1]
        if bloom < 1 or not len(l2):
            continue
        p = np.array([bloom_fpr(bloom, int(n[x]), form) for x in l2])
        sure = np.zeros(len(l2), np.int64)

        def probes() -> Iterator[np.ndarray]:
            for part in e.parts():
                n_left, n_right, hit_left, hit_right, _ = part.ends(l1, l2)  # noqa: B023
                certain = part.near[:, None] >= l2[None, :]  # noqa: B023
                sure[:] += certain.sum(axis=0)  # noqa: B023
                # certain queries have no probes in the bins and count whole
                yield np.where(certain, 0, np.where(hit_left[:, None], n_left, 0) + np.where(hit_right[:, None], n_right, 0))

        rate = (_binned(probes(), p, binned) + sure) / len(e)
        out += [(l1, int(x), 0.0, bloom, float(q), float(r)) for x, q, r in zip(l2, p, rate, strict=True)]
    return out


def dual_rates(e: Evidence, n: np.ndarray, m: int, lengths: Iterable[int], splits: tuple = SPLITS, firsts: Iterable[int] | None = None, alone: bool = True) -> list[tuple]:
    """(l1, l2, split, bloom, p, rate) of two Bloom filters, and of one with all the memory (l1 = 0)."""
    lengths, out = np.array(sorted(lengths), np.int64), []
    if alone:
        for x in lengths.tolist():
            p = bloom_fpr(m, int(n[x]))
            span = (e.hi >> (e.bits - x)) - (e.lo >> (e.bits - x)) + 1
            rate = np.where(e.near >= x, 1.0, 1.0 if p >= 1 else -np.expm1(span * np.log1p(-p)))
            out.append((0, x, 0.0, m, float(p), float(rate.mean())))
    for l1 in firsts if firsts is not None else lengths.tolist():
        l2 = lengths[lengths > l1]
        if not len(l2):
            continue
        size = (np.int64(1) << (l2 - l1))[None, :]
        sums = {split: np.zeros(len(l2)) for split in splits}
        bloom = {split: (int(np.floor(m * split)), bloom_fpr(int(np.floor(m * split)), int(n[l1])), np.array([bloom_fpr(m - int(np.floor(m * split)), int(n[x])) for x in l2])) for split in splits}
        for part in e.parts():
            n_left, n_right, hit_left, hit_right, all_regions = part.ends(l1, l2)
            one = ((part.lo >> (e.bits - l1)) == (part.hi >> (e.bits - l1)))[:, None]
            cut_left, cut_right = n_left < size, ~one & (n_right < size)
            full = all_regions[:, None] - cut_left - cut_right
            certain = part.near[:, None] >= l2[None, :]
            for split, (_, p1, p2) in bloom.items():
                with np.errstate(divide="ignore"):
                    no = np.log1p(-np.minimum(p2, 1 - 1e-16))[None, :]
                keep_left, keep_right = np.exp(n_left * no), np.exp(n_right * no)
                left = np.where(cut_left, np.where(hit_left[:, None], keep_left, (1 - p1) + p1 * keep_left), 1.0)
                right = np.where(cut_right, np.where(hit_right[:, None], keep_right, (1 - p1) + p1 * keep_right), 1.0)
                inner = np.exp(np.maximum(full, 0) * np.log1p(np.maximum(p1 * np.expm1(size * no), -1 + 1e-16)))
                sums[split] += np.where(certain, 1.0, 1 - left * right * inner).sum(axis=0)
        for split, (m1, _, p2) in bloom.items():
            out += [(int(l1), int(x), split, m - m1, float(q), float(r)) for x, q, r in zip(l2, p2, sums[split] / len(e), strict=True)]
    return out


def best_of(rates: list[tuple], tie: str = "last") -> tuple:
    """The design of the smallest rate at nine digits; of equal ones the later or the earlier."""
    sign = -1 if tie == "last" else 1
    return min(rates, key=lambda r: (round(r[5], 9), sign * r[0], sign * r[1], r[2]))


def default_design(n: np.ndarray, m: int, bits: int) -> tuple:
    """Of a run without empty samples: one Bloom filter of whole keys, which serves points and the shortest ranges."""
    return (0, bits, 0.0, m, bloom_fpr(m, int(n[bits])), None)


def tune_run(codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, bits: int, bpk: float, kind: str = "hybrid", grid: Iterable[int] | None = None, binned: bool = True, form: str = "load_aware") -> tuple[list[tuple], tuple, dict]:
    """Rates of all designs of a kind, the best one, and what each stage took (milliseconds).

    Kinds: ``hybrid``, ``single``, ``trie``, ``dual``.
    """
    took, began = {}, time.perf_counter()

    def lap(stage: str) -> None:
        nonlocal began
        took[stage], began = (time.perf_counter() - began) * 1e3, time.perf_counter()

    m, lengths = int(np.floor(len(codes) * bpk)), list(grid) if grid is not None else list(range(1, bits + 1))
    n = key_prefix_counts(codes, bits)
    lap("count_keys")
    tries, dense = trie_memory(n, bits) if kind in ("hybrid", "trie") else (np.zeros(bits + 1, np.int64),) * 2
    lap("trie_memory")
    e = Evidence(codes, lo, hi, bits)
    lap("count_queries")
    if not len(e):
        rates = []
    elif kind == "dual":
        rates = dual_rates(e, n, m, lengths)
    else:
        rates = hybrid_rates(e, n, tries, m, lengths if kind != "trie" else [], [0] if kind == "single" else None, binned, form)
    best = best_of(rates) if rates else default_design(n, m, bits)
    lap("rates")
    return rates, best, took | {"dense": dense, "tries": tries, "m": m}


def shared_sample(sample: DataFrame):
    """Bounds of a bounded sample, broadcast; a sample beyond ``MAX_SAMPLE`` is refused, as a queue never grows so far."""
    rows = sample.select("lo", "hi").where("lo is not null and hi is not null").orderBy("lo", "hi").limit(MAX_SAMPLE + 1).toArrow()
    if rows.num_rows > MAX_SAMPLE:
        raise ValueError(f"a sample holds {MAX_SAMPLE} queries at most")
    return sample.sparkSession.sparkContext.broadcast((rows.column("lo").to_numpy(), rows.column("hi").to_numpy()))


def all_rates(keys: DataFrame, sample: DataFrame, bits: int, bpk: float, kind: str = "hybrid", **options) -> DataFrame:
    """Rates of all designs of every run: run_id, l1, l2, split, bloom, p, exp_fpr (nine digits)."""
    shared = shared_sample(sample)

    def run(key, table):
        codes = np.unique(table.column("code").to_numpy())
        rates, _, _ = tune_run(codes, *shared.value, bits, bpk, kind, **options)
        l1, l2, split, bloom, p, r = zip(*rates, strict=True) if rates else ((),) * 6
        types = (pa.int32(), pa.int32(), pa.float64(), pa.int64(), pa.float64(), pa.float64())
        names = ("l1", "l2", "split", "bloom", "p", "exp_fpr")
        return pa.table({"run_id": pa.array([key[0].as_py()] * len(l1), pa.int64())} | {c: pa.array(x, t) for c, x, t in zip(names, (l1, l2, split, bloom, p, [round(x, 9) for x in r]), types, strict=True)})

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, RATES)


def chosen(keys: DataFrame, sample: DataFrame, bits: int, bpk: float, kind: str = "hybrid", **options) -> DataFrame:
    """The best design of every run: run_id, l1, l2, split, bloom, p, exp_fpr (null without empty samples)."""
    shared = shared_sample(sample)

    def run(key, table):
        codes = np.unique(table.column("code").to_numpy())
        _, b, _ = tune_run(codes, *shared.value, bits, bpk, kind, **options)
        return pa.table({"run_id": pa.array([key[0].as_py()], pa.int64()), "l1": pa.array([b[0]], pa.int32()), "l2": pa.array([b[1]], pa.int32()), "split": pa.array([b[2]]), "bloom": pa.array([b[3]], pa.int64()), "p": pa.array([b[4]], pa.float64()), "exp_fpr": pa.array([None if b[5] is None else round(b[5], 9)], pa.float64())})

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, RATES)


def built(codes: np.ndarray, bits: int, kind: str, best: tuple, told: dict) -> dict:
    """The filter of a chosen design, as columns of ``FILTER``; its trie is the level-order blob, its size what is stored."""
    l1, l2, split, bloom, _, _ = best
    lengths, memory = ([l2], [bloom]) if l2 else ([], [])
    if kind == "dual" and l1:
        lengths, memory = [l1, l2], [told["m"] - bloom, bloom]
    blooms = [filters.Bloom.of_prefixes(codes, bits, x, y) for x, y in zip(lengths, memory, strict=True)]
    depth = l1 if kind in ("hybrid", "trie") else 0
    blob = trie.encode_tails(filters.prefixes_of(codes, bits, depth), depth, int(told["dense"][depth])) if depth else b""
    return {"kind": "hybrid" if depth else "levels", "lengths": lengths, "depth": depth, "m": [b.m for b in blooms], "h": [b.h for b in blooms], "words": [b.packed() for b in blooms], "trie": blob, "aux": b"", "n_keys": len(codes), "bits": sum(b.m for b in blooms) + trie.stored_bits(blob)}


def build_run_filters(keys: DataFrame, sample: DataFrame, bits: int, bpk: float = 10, kind: str = "hybrid", **options) -> DataFrame:
    """Filters of all runs, each tuned on the sample's queries that are empty in it: ``FILTER``, exp_fpr, stage times."""
    shared = shared_sample(sample)

    def run(key, table):
        codes = np.unique(table.column("code").to_numpy())
        _, best, told = tune_run(codes, *shared.value, bits, bpk, kind, **options)
        began = time.perf_counter()
        row = {"run_id": key[0].as_py()} | built(codes, bits, kind, best, told) | {"exp_fpr": best[5]}
        told["build"] = (time.perf_counter() - began) * 1e3
        row |= {f"{s}_ms": told[s] for s in STAGES}
        return pa.Table.from_pylist([row], pa.schema([*filters.FILTER_ARROW, ("exp_fpr", pa.float64()), *((f"{s}_ms", pa.float64()) for s in STAGES)]))

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, BUILT)


def modelling_share(built_filters: DataFrame) -> DataFrame:
    """Milliseconds of each stage over all runs, their sum, and the share of all but the build."""
    sums = built_filters.agg(*[F.sum(f"{s}_ms").alias(s) for s in STAGES], F.sum("n_keys").alias("n_keys"))
    total = sum((F.col(s) for s in STAGES[1:]), F.col(STAGES[0]))
    return sums.withColumns({"total": total, "modelling_share": (total - F.col("build")) / total})
