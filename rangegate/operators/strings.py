"""Filters of string keys: lexicographic order, keys and bounds padded with null bytes to one width, prefixes of any bits.

A padded string of ``width`` bytes is a number of ``8 * width`` bits; distances between bounds are taken on whole numbers
and regions counted in floating point, which is exact up to 2^53 and precise enough beyond, where a rate is 1 anyway.
A short key and its padded twin cannot be told apart: that may cost a false positive, never a false negative.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangegate.functions.amq import bloom_fpr, num_hashes
from rangegate.functions.hashes import mix64
from rangegate.functions.keys import bit_length_numpy
from rangegate.operators.construct import _binned, best_of, key_prefix_counts, trie_memory

CAP = 1 << 12
MAX_SAMPLE = 1_000_000
RESULT = "run_id long, kind string, l1 int, l2 int, exp_fpr double, obs_fpr double, n_empty long, false_negatives long, bpk double, model_ms double"


def padded(values: list[bytes], width: int) -> np.ndarray:
    """Strings cut or padded with null bytes to ``width``."""
    return np.array([v[:width] for v in values], f"S{width}")


def matrix(strings: np.ndarray) -> np.ndarray:
    return np.frombuffer(strings.tobytes(), np.uint8).reshape(len(strings), strings.itemsize)


def numbers(strings: np.ndarray) -> list[int]:
    width = strings.itemsize
    data = strings.tobytes()
    return [int.from_bytes(data[i : i + width], "big") for i in range(0, len(data), width)]


def lcp_bits(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common prefix of strings of one width, in bits."""
    if not len(a):
        return np.zeros(0, np.int64)
    x = matrix(a) ^ matrix(b)
    at = (x != 0).argmax(axis=1)
    byte = x[np.arange(len(x)), at]
    return np.where(byte == 0, 8 * a.itemsize, 8 * at + 8 - bit_length_numpy(byte))


def prefix_counts(sorted_keys: np.ndarray) -> np.ndarray:
    """Distinct prefixes of 0 .. k bits."""
    bits = 8 * sorted_keys.itemsize
    if not len(sorted_keys):
        return np.zeros(bits + 1, np.int64)
    return 1 + np.cumsum(np.bincount(lcp_bits(sorted_keys[1:], sorted_keys[:-1]) + 1, minlength=bits + 2)[: bits + 1])


def scaled(values: list[int], shift: np.ndarray) -> np.ndarray:
    """values / 2^shift, one row a value and one column a shift; at most 2^62."""
    length = np.array([max(0, v.bit_length() - 53) for v in values], np.int64)
    head = np.array([float(v >> n) for v, n in zip(values, length.tolist(), strict=True)])
    power = length[:, None] - shift[None, :]
    return np.minimum(np.where(power > 62, 2.0**62, np.ldexp(head[:, None], np.clip(power, -2000, 62).astype(np.int32))), 2.0**62)


class StringEvidence:
    """A run's view of string queries."""

    def __init__(self, keys: np.ndarray, lo: np.ndarray, hi: np.ndarray, lengths: list[int]):
        self.bits = 8 * keys.itemsize
        at = np.searchsorted(keys, lo)
        inside = np.minimum(at, max(0, len(keys) - 1))
        self.empty = (at == len(keys)) | (keys[inside] > hi) if len(keys) else np.ones(len(lo), bool)
        at, self.lo, self.hi = at[self.empty], lo[self.empty], hi[self.empty]
        none = np.zeros(len(at), np.int64)
        self.left = np.where(at > 0, lcp_bits(self.lo, keys[np.maximum(at - 1, 0)]), 0) if len(keys) else none
        self.right = np.where(at < len(keys), lcp_bits(self.hi, keys[np.minimum(at, len(keys) - 1)]), 0) if len(keys) else none
        self.near, self.own = np.maximum(self.left, self.right), lcp_bits(self.lo, self.hi)
        self.low, self.high, self.lengths = numbers(self.lo), numbers(self.hi), np.array(lengths)
        self.span = np.array([[float(min((b >> (self.bits - x)) - (a >> (self.bits - x)) + 1, 1 << 62)) for x in lengths] for a, b in zip(self.low, self.high, strict=True)]).reshape(len(self.low), len(lengths))

    def probes(self, l1: int) -> np.ndarray:
        """Bloom probes of each query for every length over ``l1`` under a trie of that depth."""
        use = self.lengths > l1
        shift, one = self.bits - self.lengths[use], self.own >= l1
        size = 1 << (self.bits - l1)
        n_left = np.ceil(scaled([size - (a & (size - 1)) for a in self.low], shift))
        n_right = np.floor(scaled([b & (size - 1) for b in self.high], shift)) + 1
        hit_left, hit_right = np.where(one, self.near >= l1, self.left >= l1), ~one & (self.right >= l1)
        return np.where(hit_left[:, None], np.where(one[:, None], self.span[:, use], n_left), 0) + np.where(hit_right[:, None], n_right, 0)


def rates(e: StringEvidence, n: np.ndarray, tries: np.ndarray, m: int, tries_on: bool = True) -> list[tuple]:
    """(l1, l2, 0, bloom, p, rate) of all designs over the given Bloom lengths and all depths that fit."""
    out = []
    for l1 in np.flatnonzero(tries <= m).tolist() if tries_on else [0]:
        bloom, l2 = m - int(tries[l1]), e.lengths[e.lengths > l1]
        if l1:
            out.append((l1, 0, 0.0, 0, 0.0, float((e.near >= l1).mean())))
        if bloom < 1 or not len(l2):
            continue
        p = np.array([bloom_fpr(bloom, int(n[x])) for x in l2])
        certain = e.near[:, None] >= l2[None, :]
        probes = np.where(certain, 0, np.minimum(e.probes(l1), 2.0**53)).astype(np.int64)
        rate = (_binned([probes], p, True) + certain.sum(axis=0)) / len(e.near)
        out += [(l1, int(x), 0.0, bloom, float(q), float(r)) for x, q, r in zip(l2, p, rate, strict=True)]
    return out


def prefix_hash(values: np.ndarray, length: int) -> np.ndarray:
    """64-bit hash of the first ``length`` bits of each row of bytes."""
    size = -(-length // 8)
    part = values[:, :size].astype(np.uint64)
    if length % 8:
        part[:, -1] &= np.uint64(0xFF << (8 - length % 8) & 0xFF)
    with np.errstate(over="ignore"):
        powers = np.cumprod(np.full(size, 0x9E3779B97F4A7C15, np.uint64), dtype=np.uint64)
        return mix64((part * powers[None, :]).sum(axis=1, dtype=np.uint64).view(np.int64), length)


class StringBloom:
    """Bloom filter over prefixes of one length."""

    def __init__(self, keys: np.ndarray, length: int, m: int):
        self.length, self.m = length, max(1, int(m))
        x = np.unique(prefix_hash(keys, length))
        self.h, self.bits = num_hashes(self.m, len(x)), np.zeros(self.m, bool)
        for at in self._places(x):
            self.bits[at] = True

    def _places(self, x: np.ndarray) -> Iterator[np.ndarray]:
        first, step = (x >> np.uint64(2)).astype(np.int64) % self.m, 1 + (mix64(x.view(np.int64), 3) >> np.uint64(2)).astype(np.int64) % max(1, self.m - 1)
        return ((first + i * step) % self.m for i in range(self.h))

    def any_of(self, first: int, last: int, bits: int) -> bool:
        """Whether some prefix in first .. last may be held; yes without asking beyond ``CAP``."""
        if last - first >= CAP:
            return True
        size, pad = -(-self.length // 8), -self.length % 8
        raw = b"".join(((p << pad).to_bytes(size, "big")) for p in range(first, last + 1))
        x = prefix_hash(np.frombuffer(raw, np.uint8).reshape(-1, size), self.length)
        return bool(np.logical_and.reduce([self.bits[at] for at in self._places(x)]).any())


def answer(keys: np.ndarray, design: tuple, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """maybe of each query under a design (l1, l2, bloom bits)."""
    l1, l2, m = design
    bits, held = 8 * keys.itemsize, numbers(keys)
    trie = {x >> (bits - l1) for x in held} if l1 else None
    order = sorted(trie) if trie else []
    bloom = StringBloom(matrix(keys), l2, m) if l2 else None
    out = np.zeros(len(lo), bool)
    from bisect import bisect_left, bisect_right

    for i, (a, b) in enumerate(zip(numbers(lo), numbers(hi), strict=True)):
        if trie is None:
            out[i] = bloom.any_of(a >> (bits - l2), b >> (bits - l2), bits)
            continue
        a0, b0 = a >> (bits - l1), b >> (bits - l1)
        if bisect_left(order, b0) > bisect_right(order, a0):
            out[i] = True
            continue
        for p in {a0, b0} & trie:
            if bloom is None:
                out[i] = True
                break
            d, f, z = l2 - l1, a >> (bits - l2), b >> (bits - l2)
            if bloom.any_of(max(f, p << d), min(z, ((p + 1) << d) - 1), bits):
                out[i] = True
                break
    return out


def unique_lengths(keys: np.ndarray) -> np.ndarray:
    """Bytes of the minimal distinguishing prefix of each sorted key."""
    own = lcp_bits(keys[1:], keys[:-1]) // 8
    return np.minimum(keys.itemsize, np.maximum(np.r_[-1, own], np.r_[own, -1]) + 1)


def unique_answer(keys: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, float]:
    """maybe of each query under unique prefixes, and their bits a key (10 a label)."""
    n, m = unique_lengths(keys), matrix(keys)
    low = np.where(np.arange(keys.itemsize)[None, :] < n[:, None], m, 0).astype(np.uint8)
    high = np.where(np.arange(keys.itemsize)[None, :] < n[:, None], m, 255).astype(np.uint8)
    low, high = (np.frombuffer(x.tobytes(), f"S{keys.itemsize}") for x in (low, high))
    at = np.searchsorted(high, lo)
    inside = np.minimum(at, len(keys) - 1)
    labels = sum(len(np.unique(keys[n >= j].astype(f"S{j}"))) for j in range(1, int(n.max()) + 1))
    return (at < len(keys)) & (low[inside] <= hi), 10 * labels / len(keys)


def string_report(keys: DataFrame, queries: DataFrame, width: int, bpk: float = 10, grid: list[int] | None = None) -> DataFrame:
    """For each run of ``keys(run_id, code binary)`` and a bounded sample ``queries(lo, hi)`` binary: the hybrid, the single
    filter, the trie alone and unique prefixes, with expected and observed rates and the time of modelling.

    ``grid`` gives the Bloom lengths that are tried; the default is 128 lengths over the whole width.
    """
    bits = 8 * width
    lengths = sorted(set(grid or np.linspace(bits / 128, bits, min(128, bits)).round().astype(int).tolist()))
    rows = queries.select("lo", "hi").limit(MAX_SAMPLE + 1).toArrow()
    if rows.num_rows > MAX_SAMPLE:
        raise ValueError(f"a sample holds {MAX_SAMPLE} queries at most")
    shared = keys.sparkSession.sparkContext.broadcast((rows.column("lo").to_pylist(), rows.column("hi").to_pylist()))

    def run(key, table):
        own = np.unique(padded(table.column("code").to_pylist(), width))
        lo, hi = (padded(x, width) for x in shared.value)
        began = time.perf_counter()
        n = prefix_counts(own)
        tries, _ = trie_memory(n, bits)
        m = int(len(own) * bpk)
        e = StringEvidence(own, lo, hi, lengths)
        found, out = rates(e, n, tries, m) if len(e.near) else [], []
        model = (time.perf_counter() - began) * 1e3
        picks = {"hybrid": found, "single": [r for r in found if r[0] == 0], "trie": [r for r in found if r[1] == 0]}
        for kind, own_rates in picks.items():
            if own_rates:
                best = best_of(own_rates)
                maybe = answer(own, (best[0], best[1], best[3]), lo, hi)
                out.append((kind, best[0], best[1], best[5], float(maybe[e.empty].mean()), int((~maybe & ~e.empty).sum()), float(bpk), model))
        maybe, cost = unique_answer(own, lo, hi)
        out.append(("unique_prefix", 0, 0, None, float(maybe[e.empty].mean()) if e.empty.any() else None, int((~maybe & ~e.empty).sum()), cost, 0.0))
        kind, l1, l2, expected, observed, wrong, cost, took = zip(*out, strict=True)
        k = len(out)
        return pa.table({"run_id": pa.array([key[0].as_py()] * k, pa.int64()), "kind": pa.array(kind), "l1": pa.array(l1, pa.int32()), "l2": pa.array(l2, pa.int32()), "exp_fpr": pa.array(expected, pa.float64()), "obs_fpr": pa.array(observed, pa.float64()), "n_empty": pa.array([int(e.empty.sum())] * k, pa.int64()), "false_negatives": pa.array(wrong, pa.int64()), "bpk": pa.array(cost, pa.float64()), "model_ms": pa.array(took, pa.float64())})

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, RESULT)


def shifted(rows: DataFrame, width: int) -> DataFrame:
    """qid, lo, hi of ``rows(qid, code, up, w)``: the padded string ``code`` moved up by ``up``, and by ``w`` more, as numbers."""

    def run(batches: Iterator) -> Iterator:
        for batch in batches:
            low, high, top = [], [], (1 << (8 * width)) - 1
            for code, up, w in zip(*(batch.column(c).to_pylist() for c in ("code", "up", "w")), strict=True):
                a = min(int.from_bytes(code[:width].ljust(width, b"\0"), "big") + up, top)
                low.append(a.to_bytes(width, "big"))
                high.append(min(a + w, top).to_bytes(width, "big"))
            yield pa.RecordBatch.from_arrays([batch.column("qid"), pa.array(low, pa.binary()), pa.array(high, pa.binary())], ["qid", "lo", "hi"])

    return rows.select(F.col("qid").cast("long"), "code", F.col("up").cast("long"), F.col("w").cast("long")).mapInArrow(run, "qid long, lo binary, hi binary")
