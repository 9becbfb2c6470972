"""Filters of key runs: one build and one vectorised probe per run, filters co-grouped with the queries of their run.

A filter is a list of prefix levels with one Bloom filter each, or a trie depth with one Bloom level, or unique prefixes.
One level is the single filter, two are the dual filter, several are the hierarchical filter; the level of all bits is
the whole-key filter. A run is bounded by the store, so a filter is built in one task; its bits stay packed when probed.
Filters of up to 2^31 bits take the 31-bit arithmetic hash that oracles know, larger ones a 64-bit hash.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangegate.functions.amq import num_hashes
from rangegate.functions.hashes import PART, hash_pair, mix64, mix_numpy, next_place, places, raw_pair, start_and_step
from rangegate.functions.keys import bit_length_numpy

PROBE_CAP = 1 << 16
DYADIC_CAP = 1 << 10
#: Filters of more bits are filled packed; smaller ones with a byte a bit, which is faster.
UNPACKED = 1 << 26
#: Probes that are laid out at a time.
PROBES = 1 << 19
FILTER = "run_id long, kind string, lengths array<int>, depth int, m array<long>, h array<int>, words array<binary>, trie binary, aux binary, n_keys long, bits long"
FILTER_ARROW = [("run_id", pa.int64()), ("kind", pa.string()), ("lengths", pa.list_(pa.int32())), ("depth", pa.int32()), ("m", pa.list_(pa.int64())), ("h", pa.list_(pa.int32())), ("words", pa.list_(pa.binary())), ("trie", pa.binary()), ("aux", pa.binary()), ("n_keys", pa.int64()), ("bits", pa.int64())]


def _prefix(x: np.ndarray, bits: int, length: int) -> np.ndarray:
    return x >> (bits - length) if length else np.zeros_like(x)


def prefix_parts(codes: np.ndarray, bits: int, length: int) -> Iterator[np.ndarray]:
    """The distinct prefixes of sorted codes, ascending, in parts of bounded size."""
    for a in range(0, len(codes), PART):
        x = _prefix(codes[max(0, a - 1) : a + PART], bits, length)
        yield x[1:][x[1:] != x[:-1]] if a else x[np.r_[True, x[1:] != x[:-1]]]


def prefixes_of(codes: np.ndarray, bits: int, length: int) -> np.ndarray:
    """The distinct prefixes of sorted codes, ascending."""
    out, at = np.empty(sum(len(x) for x in prefix_parts(codes, bits, length)), np.int64), 0
    for x in prefix_parts(codes, bits, length):
        out[at : at + len(x)] = x
        at += len(x)
    return out


def prefix_hashes(codes: np.ndarray, bits: int, length: int) -> tuple[np.ndarray, np.ndarray]:
    """The ``raw_pair`` of the distinct prefixes of sorted codes, for filters of up to 2^31 bits."""
    parts = [raw_pair(x, 1) for x in prefix_parts(codes, bits, length)]
    return tuple(np.concatenate([np.zeros(0, np.uint32), *(p[i] for p in parts)]) for i in (0, 1))


@dataclass
class Bloom:
    """Bloom filter with packed bits."""

    m: int
    h: int
    data: np.ndarray = field(repr=False)

    @staticmethod
    def of(values: np.ndarray, m: int) -> Bloom:
        return Bloom.of_hashes(*raw_pair(np.unique(values), int(m)), m)

    @staticmethod
    def of_hashes(first: np.ndarray, step: np.ndarray, m: int) -> Bloom:
        """Of distinct elements, by their ``raw_pair``."""
        parts = ((first[at : at + PART], step[at : at + PART]) for at in range(0, len(first), PART))
        return Bloom._set(parts, len(first), max(int(m), 1))

    @staticmethod
    def of_prefixes(codes: np.ndarray, bits: int, length: int, m: int) -> Bloom:
        """Of the prefixes of sorted codes; they are never held all at once."""
        m, n = max(int(m), 1), sum(len(x) for x in prefix_parts(codes, bits, length))
        return Bloom._set((raw_pair(x, m) for x in prefix_parts(codes, bits, length)), n, m)

    @staticmethod
    def _set(parts: Iterable[tuple[np.ndarray, np.ndarray]], n: int, m: int) -> Bloom:
        h = num_hashes(m, n)
        if m <= UNPACKED:
            bits = np.zeros(m, bool)
            for first, step in parts:
                for at in places(first, step, m, h):
                    bits[at] = True
            return Bloom(m, h, np.packbits(bits))
        data = np.zeros(m + 7 >> 3, np.uint8)
        for first, step in parts:
            for at in places(first, step, m, h):
                byte, bit = (at >> 3).astype(np.int64), np.uint8(128) >> (at & 7).astype(np.uint8)
                while len(byte):  # of places in one byte only the last is kept; the others go again
                    data[byte] |= bit
                    lost = np.flatnonzero(data[byte] & bit == 0)
                    byte, bit = byte[lost], bit[lost]
        return Bloom(m, h, data)

    @staticmethod
    def read(m: int, h: int, data: bytes) -> Bloom:
        return Bloom(m, h, np.frombuffer(data, np.uint8))

    def packed(self) -> bytes:
        return self.data.tobytes()

    def test(self, values: np.ndarray) -> np.ndarray:
        out = np.zeros(len(values), bool)
        for a in range(0, len(values), PART):
            at, step = start_and_step(*raw_pair(values[a : a + PART], self.m), self.m)
            live = np.arange(a, a + len(at))
            for i in range(self.h):
                at = next_place(at, step, self.m) if i else at
                yes = np.flatnonzero(self.data[at >> 3] << (at & 7).astype(np.uint8) & 128)
                live, at, step = live[yes], at[yes], step[yes]
            out[live] = True
        return out


@dataclass
class BlockedBloom:
    """Bloom filter in blocks of 512 bits: all bits of an element lie in one cache line."""

    m: int
    h: int
    data: np.ndarray = field(repr=False)

    @staticmethod
    def _places(values: np.ndarray, m: int, h: int) -> list[np.ndarray]:
        x = mix64(values)
        block = (x >> np.uint64(33)).astype(np.int64) % max(1, m // 512) * 512
        a, b = (x & np.uint64(511)).astype(np.int64), ((x >> np.uint64(9)) & np.uint64(511)).astype(np.int64) | 1
        return [block + (a + i * b) % 512 for i in range(h)]

    @staticmethod
    def of(values: np.ndarray, m: int) -> BlockedBloom:
        values = np.unique(values)
        m = max(512, int(m) // 512 * 512)
        h, bits = num_hashes(m, len(values)), np.zeros(m, bool)
        for at in BlockedBloom._places(values, m, h):
            bits[at] = True
        return BlockedBloom(m, h, bits)

    def test(self, values: np.ndarray) -> np.ndarray:
        return np.logical_and.reduce([self.data[at] for at in self._places(values, self.m, self.h)])


@dataclass
class XorFilter:
    """Three-way xor filter: an element's fingerprint is the xor of one slot in each third of the table."""

    bits: int
    seed: int
    slots: np.ndarray = field(repr=False)

    @property
    def m(self) -> int:
        return self.bits * len(self.slots)

    @staticmethod
    def _places(values: np.ndarray, seed: int, third: int) -> tuple[np.ndarray, np.ndarray]:
        x = mix64(values, seed)
        at = [(mix64(x.view(np.int64), 7 * i + 1) >> np.uint64(32)) * np.uint64(third) >> np.uint64(32) for i in range(3)]
        return np.stack([a.astype(np.int64) + i * third for i, a in enumerate(at)]), x

    @staticmethod
    def of(values: np.ndarray, m: int) -> XorFilter:
        """Of ``m`` bits at most; peels slots that one element has left, layer by layer."""
        values = np.unique(values)
        third = max(2, int(math.ceil((1.23 * len(values) + 32) / 3)))
        bits = max(1, min(32, int(m) // (3 * third)))
        for seed in range(64):
            at, x = XorFilter._places(values, seed, third)
            mark = (x & np.uint64((1 << bits) - 1)).astype(np.int64)
            left, layers = np.ones(len(values), bool), []
            while left.any():
                use = np.bincount(at[:, left].ravel(), minlength=3 * third)
                lone = use[at] == 1
                pick = left & lone.any(axis=0)
                if not pick.any():
                    break
                rows = np.flatnonzero(pick)
                layers.append((rows, at[lone[:, rows].argmax(axis=0), rows]))
                left[rows] = False
            if left.any():
                continue
            slots = np.zeros(3 * third, np.int64)
            for rows, own in layers[::-1]:
                slots[own] = 0
                slots[own] = mark[rows] ^ np.bitwise_xor.reduce(slots[at[:, rows]], axis=0)
            return XorFilter(bits, seed, slots)
        raise RuntimeError("no seed peels the table")

    def test(self, values: np.ndarray) -> np.ndarray:
        at, x = self._places(values, self.seed, len(self.slots) // 3)
        return np.bitwise_xor.reduce(self.slots[at], axis=0) == (x & np.uint64((1 << self.bits) - 1)).astype(np.int64)


#: Kinds that can be built, all with ``of(values, m)`` and ``test(values)``.
BUILDERS = {"bloom": Bloom, "blocked_bloom": BlockedBloom, "xor": XorFilter}


@dataclass
class CountingBloom:
    """Counters of a few bits in place of bits; a counter at its largest value stays there, so counts are upper bounds."""

    h: int
    top: int
    counters: np.ndarray = field(repr=False)

    @staticmethod
    def of(prefixes: np.ndarray, m: int, counter_bits: int = 4) -> CountingBloom:
        """Of all prefixes with their repeats, in ``m`` bits."""
        slots, top = max(1, int(m) // counter_bits), (1 << counter_bits) - 1
        distinct, n = np.unique(prefixes, return_counts=True)
        h = num_hashes(slots, len(distinct))
        counters, (first, step) = np.zeros(slots, np.int64), hash_pair(distinct, slots)
        for i in range(h):
            np.add.at(counters, (first + i * step) % slots, n)
        return CountingBloom(h, top, np.minimum(counters, top))

    def count(self, prefixes: np.ndarray) -> np.ndarray:
        """At least the number of keys under each prefix, unless a counter is full (``top``)."""
        first, step = hash_pair(prefixes, len(self.counters))
        return np.min([self.counters[(first + i * step) % len(self.counters)] for i in range(self.h)], axis=0)

    def range_count(self, first: int, last: int) -> int:
        """Upper bound of the keys under the prefixes first .. last, with ``top`` for a full counter."""
        return int(self.count(np.arange(first, last + 1)).sum())


def spread(first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Owner and value of every integer in the ranges [first, first + count)."""
    owner = np.repeat(np.arange(len(first)), count)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count) + first[owner]


def spread_parts(first: np.ndarray, count: np.ndarray, most: int = PROBES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``spread`` of some ranges after the other, of ``most`` integers at a time, or of one range."""
    a, ends = 0, np.cumsum(count)
    while a < len(first):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + most, side="right")))
        owner, value = spread(first[a:b], count[a:b])
        yield owner + a, value
        a = b


@dataclass
class Asked:
    """Queries on their way through the levels of a filter: probes made, those answered yes, and the regions that said yes."""

    probes: np.ndarray
    sure: np.ndarray
    owner: np.ndarray
    region: np.ndarray | None = None
    above: int = 0

    @staticmethod
    def of(n: int) -> Asked:
        return Asked(np.zeros(n, np.int64), np.zeros(n, bool), np.arange(n))

    def level(self, bloom: Bloom, length: int, bits: int, lo: np.ndarray, hi: np.ndarray, cap: int, last_one: bool = False) -> Asked:
        """After one more level, deeper than those before; the regions of the last one are not kept."""
        n, owner = len(lo), self.owner
        first, last = _prefix(lo, bits, length)[owner], _prefix(hi, bits, length)[owner]
        if self.region is not None:
            d = length - self.above
            first, last = np.maximum(first, self.region << d), np.minimum(last, ((self.region + 1) << d) - 1)
        count = last - first + 1
        sure = self.sure | (np.bincount(owner, count.astype(np.float64), n) > cap)
        keep = ~sure[owner]
        owner, probes, owners, regions = owner[keep], self.probes.copy(), [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for at, value in spread_parts(first[keep], count[keep]):
            asking, yes = owner[at], bloom.test(value)
            probes += np.bincount(asking, minlength=n)
            owners.append(np.unique(asking[yes]) if last_one else asking[yes])
            regions.append(value[yes][: 0 if last_one else None])
        return Asked(probes, sure, np.concatenate(owners), np.concatenate(regions), length)

    @property
    def maybe(self) -> np.ndarray:
        out = self.sure.copy()
        out[self.owner] = True
        return out


def probe_levels(blooms: list, lengths: list[int], bits: int, lo: np.ndarray, hi: np.ndarray, cap: int = PROBE_CAP) -> tuple[np.ndarray, np.ndarray]:
    """Whether each query may hold a key, and the Bloom probes made; regions that say yes are expanded one level down.

    A query that would need more than ``cap`` probes at a level is answered yes, which is never wrong.
    """
    asked = Asked.of(len(lo))
    for bloom, length in zip(blooms, lengths, strict=True):
        asked = asked.level(bloom, length, bits, lo, hi, cap, length == lengths[-1])
    return asked.maybe, asked.probes


def probe_dyadic(blooms: list, bits: int, lo: np.ndarray, hi: np.ndarray, cap: int = DYADIC_CAP) -> tuple[np.ndarray, np.ndarray]:
    """Hierarchical filter over the deepest levels, the last of all bits: maybe and probes.

    A query is the union of its dyadic blocks; each is asked at its own level, a yes at its two halves, down to single
    keys, until one key says yes. A block above the first stored level counts as yes and goes to its halves.
    Queries are taken together, level by level; blocks of a level above hand their halves down. A query with more than
    ``cap`` open blocks at one level is answered yes, which is never wrong: one of so many leaves says yes anyway.
    """
    n, top = len(lo), bits - len(blooms) + 1
    maybe, probes = np.zeros(n, bool), np.zeros(n, np.int64)
    low, high = lo.copy(), hi + 1
    blocks: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {length: [] for length in range(bits + 1)}
    for length in range(bits, -1, -1):  # canonical blocks: an odd left end and an odd right end leave one each
        live = np.flatnonzero(low < high)
        left = live[(low[live] & 1 == 1) | (length == 0)]
        blocks[length].append((left, low[left]))
        low[left] += 1
        right = live[(high[live] & 1 == 1) & (low[live] < high[live])]
        blocks[length].append((right, high[right] - 1))
        high[right] -= 1
        low, high = low >> 1, high >> 1
    owner, block = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for length in range(bits + 1):
        fresh = [(q[~maybe[q]], b[~maybe[q]]) for q, b in blocks[length]]
        owner, block = (np.concatenate([x, *(b[i] for b in fresh)]) for i, x in ((0, owner), (1, block)))
        if length >= top and len(owner):
            np.add.at(probes, owner, 1)
            yes = blooms[length - top].test(block)
            owner, block = owner[yes], block[yes]
        if length < bits and len(owner):
            maybe |= np.bincount(owner, minlength=n) > cap
            live = ~maybe[owner]
            owner, block = owner[live], block[live]
            owner, block = np.repeat(owner, 2), np.stack([block << 1, (block << 1) | 1], axis=1).ravel()
    maybe[owner] = True
    return maybe, probes


def probe_hybrid(trie: np.ndarray, depth: int, bloom, length: int, bits: int, lo: np.ndarray, hi: np.ndarray, cap: int = PROBE_CAP) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """maybe, trie visits, Bloom probes. ``trie`` holds the sorted prefixes of ``depth`` bits.

    A prefix strictly between the ends lies inside the query and proves a key.
    """
    a0, a1 = _prefix(lo, bits, depth), _prefix(hi, bits, depth)
    inside = np.searchsorted(trie, a1) > np.searchsorted(trie, a0, side="right")
    has = lambda x: (trie[np.minimum(np.searchsorted(trie, x), len(trie) - 1)] == x) if len(trie) else np.zeros(len(x), bool)
    hit_l, hit_r = has(a0), has(a1) & (a1 != a0)
    visits = np.where(a0 == a1, 1, 2) + (a1 - a0 > 1)
    probes = np.zeros(len(lo), np.int64)
    if bloom is None:
        return inside | hit_l | hit_r, visits, probes
    d = length - depth
    f, l = _prefix(lo, bits, length), _prefix(hi, bits, length)
    maybe = inside.copy()
    for hit, first, last in ((hit_l, f, np.minimum(l, ((a0 + 1) << d) - 1)), (hit_r, np.maximum(f, a1 << d), l)):
        ask = np.flatnonzero(hit & ~maybe)
        count = (last - first + 1)[ask]
        over = count > cap
        maybe[ask[over]] = True
        ask, count = ask[~over], count[~over]
        for at, value in spread_parts(first[ask], count):
            probes += np.bincount(ask[at], minlength=len(lo))
            maybe[ask[at[bloom.test(value)]]] = True
    return maybe, visits, probes


def unique_lengths(codes: np.ndarray, bits: int) -> np.ndarray:
    """Bits of the minimal distinguishing prefix of each sorted key, in whole bytes."""
    length = np.empty(len(codes), np.uint8)
    for a in range(0, len(codes), PART):
        x = codes[max(0, a - 1) : a + PART + 1]
        lcp = bits - bit_length_numpy(x[1:] ^ x[:-1])
        own = np.maximum(np.r_[[-1] if a == 0 else [], lcp], np.r_[lcp, -1][a > 0 :])[: len(codes[a : a + PART])] if len(x) > 1 else np.array([-1])
        length[a : a + PART] = np.minimum(bits, 8 * (np.maximum(own, 0).astype(np.int64) // 8 + 1))
    return length


def suffixed(length: np.ndarray, bits: int, suffix: int) -> np.ndarray:
    """Lengths with ``suffix`` further bits, as far as a key has them."""
    return np.minimum(length, bits - min(suffix, bits)) + np.uint8(suffix) if suffix else length


def unique_prefix_bits(codes: np.ndarray, bits: int, length: np.ndarray, suffix_bits: int) -> int:
    """10 bits for each distinct label of a byte level (sparse form) and the suffixes; lengths are those of sorted keys."""
    total, levels = 0, range(8, int(length.max(initial=0)) + 8, 8)
    before: dict[int, tuple[int, int]] = {}
    for a in range(0, len(codes), PART):
        part, size = codes[a : a + PART], length[a : a + PART].astype(np.int64)
        for level in levels:
            reach = size >= level - 7
            cut = np.minimum(size[reach], level)
            own = part[reach] >> (bits - cut)
            if len(own):
                total += 10 * int((before.get(level) != (int(own[0]), int(cut[0]))) + ((own[1:] != own[:-1]) | (cut[1:] != cut[:-1])).sum())
                before[level] = int(own[-1]), int(cut[-1])
    return total + suffix_bits * len(codes)


def unique_blob(codes: np.ndarray, bits: int, real: int, hashed: int) -> tuple[bytearray, bytes, int]:
    """A filter of unique prefixes: the first code of each region with the prefix lengths behind, the hash marks, and its size in bits."""
    base = unique_lengths(codes, bits)
    blob, length = bytearray(9 * len(codes)), suffixed(base, bits, real)
    low = np.frombuffer(blob, "<i8", len(codes))
    np.frombuffer(blob, np.uint8)[8 * len(codes) :] = length
    marks = np.empty(len(codes) if hashed else 0, "u1" if hashed <= 8 else "<i8")
    for a in range(0, len(codes), PART):
        part, rest = codes[a : a + PART], bits - length[a : a + PART].astype(np.int64)
        low[a : a + PART] = part >> rest << rest
        if hashed:
            marks[a : a + PART] = mix_numpy(103, part) % (1 << hashed)
    return blob, marks.tobytes(), unique_prefix_bits(codes, bits, base, real + hashed)


def probe_unique(codes: np.ndarray, length: np.ndarray, bits: int, marks: Callable | None, hash_bits: int, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Whether some prefix region meets a query; of a point also the key's hash bits must agree.

    ``codes`` are sorted, one of each region. Regions are disjoint, so the first one that ends at or behind ``lo`` is that of the first code
    from ``lo`` on or the one before. ``marks`` gives the hash bits of some of them.
    """

    def ends(i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        rest = bits - length[i].astype(np.int64)
        return codes[i] >> rest << rest, (((codes[i] >> rest) + 1) << rest) - 1

    at = np.searchsorted(codes, lo)
    at = np.where((at > 0) & (ends(np.maximum(at - 1, 0))[1] >= lo), at - 1, at)
    inside = np.minimum(at, len(codes) - 1)
    maybe = (at < len(codes)) & (ends(inside)[0] <= hi)
    if marks is not None:
        maybe &= (lo != hi) | (mix_numpy(103, lo) % (1 << hash_bits) == marks(inside))
    return maybe


def best_suffix(codes: np.ndarray, bits: int, budget: int, lo: np.ndarray, hi: np.ndarray, most: int = 8) -> tuple[int, int, float] | None:
    """(real, hashed, rate) of the suffix bits with the lowest rate on the sample's empty queries within the budget.

    None if the budget does not hold the bare trie: a filter of unique prefixes has a least size that no tuning lowers.
    """
    at = np.searchsorted(codes, lo)
    empty = (at == len(codes)) | (codes[np.minimum(at, len(codes) - 1)] > hi)
    lo, hi, found = lo[empty], hi[empty], None
    base = unique_lengths(codes, bits)
    spare = (budget - unique_prefix_bits(codes, bits, base, 0)) // max(1, len(codes))
    if spare < 0:
        return None
    for real in range(min(most, spare) + 1):
        length = suffixed(base, bits, real)
        for hashed in {0, min(most, spare - real)}:
            marks = (lambda i, h=hashed: mix_numpy(103, codes[i]) % (1 << h)) if hashed else None
            rate = float(probe_unique(codes, length, bits, marks, hashed, lo, hi).mean()) if len(lo) else 0.0
            if found is None or (rate, real + hashed) < (found[2], found[0] + found[1]):
                found = (real, hashed, rate)
    return found


def minimum_bits(codes: np.ndarray, bits: int) -> float:
    """Least bits a key of a filter of unique prefixes."""
    return unique_prefix_bits(codes, bits, unique_lengths(codes, bits), 0) / max(1, len(codes))


def build(keys: DataFrame, bits: int, designs: DataFrame) -> DataFrame:
    """Filters of all runs. ``designs``: run_id, kind, lengths, depth, m (bits a level), aux (suffix bits, hash bits).

    Kinds: ``levels`` (single, dual, whole key), ``dyadic`` (hierarchical), ``hybrid``, ``unique_prefix``. A run without
    a design gets no filter, so its queries stay unanswered; ``store.survivors`` lets such runs through.
    """
    from rangegate.operators import trie as tries

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        rows = []
        codes = np.unique(left.column("code").to_numpy())
        for d in right.to_pylist() if len(codes) else []:
            blooms = [Bloom.of_prefixes(codes, bits, n, m) for n, m in zip(d["lengths"], d["m"], strict=True)]
            trie, aux, size = b"", b"", sum(b.m for b in blooms)
            if d["kind"] == "hybrid" and d["depth"]:
                trie = tries.encode_tails(prefixes_of(codes, bits, d["depth"]), d["depth"], 0)
                size += tries.stored_bits(trie)
            if d["kind"] == "unique_prefix":
                real, hashed = d["aux"]
                trie, aux, size = unique_blob(codes, bits, real, hashed)
                trie = bytes(trie)
            rows.append({"run_id": d["run_id"], "kind": d["kind"], "lengths": d["lengths"], "depth": d["depth"], "m": [b.m for b in blooms], "h": [b.h for b in blooms] or d["aux"], "words": [b.packed() for b in blooms], "trie": trie, "aux": aux, "n_keys": len(codes), "bits": size})
        return pa.Table.from_pylist(rows, pa.schema(FILTER_ARROW))

    return keys.select("run_id", "code").groupBy("run_id").cogroup(designs.select(*[F.col(c).alias(c) for c in designs.columns]).groupBy("run_id")).applyInArrow(run, FILTER)


def answer(f: dict, bits: int, lo: np.ndarray, hi: np.ndarray, cap: int = PROBE_CAP) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """maybe, trie visits and Bloom probes of one filter row."""
    from rangegate.operators import trie as tries

    blooms = [Bloom.read(m, h, w) for m, h, w in zip(f["m"], f["h"], f["words"], strict=False)]
    none = np.zeros(len(lo), np.int64)
    if f["kind"] == "dyadic":
        maybe, probes = probe_dyadic(blooms, bits, lo, hi)
        return maybe, none, probes
    if f["kind"] == "levels" or f["kind"] == "hybrid" and not f["depth"]:
        maybe, probes = probe_levels(blooms, f["lengths"], bits, lo, hi, cap)
        return maybe, none, probes
    if f["kind"] == "hybrid":
        return probe_hybrid(tries.decode_tails(f["trie"]), f["depth"], blooms[0] if blooms else None, f["lengths"][0] if blooms else 0, bits, lo, hi, cap)
    n, hashed = len(f["trie"]) // 9, f["h"][1]
    marks = np.frombuffer(f["aux"], "u1" if hashed <= 8 else "<i8")
    return probe_unique(np.frombuffer(f["trie"], "<i8", n), np.frombuffer(f["trie"], np.uint8, n, 8 * n), bits, marks.__getitem__ if hashed else None, hashed, lo, hi), none + 1, none


def probe(filters: DataFrame, queries: DataFrame, bits: int, cap: int = PROBE_CAP) -> DataFrame:
    """qid, run_id, maybe, n_trie, n_bloom for ``queries(run_id, qid, lo, hi)``; queries move to the filters."""

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        lo, hi = right.column("lo").to_numpy(), right.column("hi").to_numpy()
        for f in left.to_pylist() if len(lo) else []:
            maybe, visits, probes = answer(f, bits, lo, hi, cap)
            out.append(pa.table({"qid": right.column("qid"), "run_id": right.column("run_id"), "maybe": pa.array(maybe), "n_trie": pa.array(visits), "n_bloom": pa.array(probes)}))
        empty = pa.table({"qid": pa.array([], pa.int64()), "run_id": pa.array([], pa.int64()), "maybe": pa.array([], pa.bool_()), "n_trie": pa.array([], pa.int64()), "n_bloom": pa.array([], pa.int64())})
        return pa.concat_tables(out).combine_chunks() if out else empty

    given = filters.select("run_id", "kind", "lengths", "depth", "m", "h", "words", "trie", "aux")
    return given.groupBy("run_id").cogroup(queries.select(*[F.col(c).alias(c) for c in ("run_id", "qid", "lo", "hi")]).groupBy("run_id")).applyInArrow(run, "qid long, run_id long, maybe boolean, n_trie long, n_bloom long")


def _design(runs: DataFrame, kind: str, lengths, m, depth=0, aux: tuple[int, int] = (0, 0)) -> DataFrame:
    as_column = lambda x: F.lit(x) if isinstance(x, int) else x
    return runs.select("run_id", F.lit(kind).alias("kind"), lengths.cast("array<int>").alias("lengths"), as_column(depth).cast("int").alias("depth"), m.cast("array<long>").alias("m"), F.array(*[F.lit(a) for a in aux]).alias("aux"))


def level_design(runs: DataFrame, lengths: list[int], shares: list[float], kind: str = "levels") -> DataFrame:
    """Designs of Bloom levels from ``runs(run_id, m)``: each level gets its share of the memory."""
    return _design(runs, kind, F.array(*[F.lit(x) for x in lengths]), F.array(*[F.floor(F.col("m") * s) for s in shares]))


def hybrid_design(chosen: DataFrame, memory: DataFrame, bits: int) -> DataFrame:
    """Designs from ``choose_design``; the trie takes what the Bloom part leaves. A run nothing was chosen for gets
    one Bloom filter of whole keys, as it has no empty sample to tune on.
    """
    rows = memory.join(chosen.select("run_id", "l1", "l2", "bloom"), "run_id", "left")
    no_bloom, none = F.coalesce(F.col("l2") == 0, F.lit(False)), F.array()
    return _design(rows, "hybrid", F.when(no_bloom, none.cast("array<int>")).otherwise(F.array(F.coalesce("l2", F.lit(bits)))), F.when(no_bloom, none.cast("array<long>")).otherwise(F.array(F.coalesce("bloom", "m"))), F.coalesce("l1", F.lit(0)))


def dual_design(chosen: DataFrame, memory: DataFrame) -> DataFrame:
    """Designs from the best row of ``tune_dual`` (run_id, l1, l2, split)."""
    rows, first = chosen.join(memory, "run_id"), F.floor(F.col("m") * F.col("split"))
    return _design(rows, "levels", F.when(F.col("l1") == 0, F.array("l2")).otherwise(F.array("l1", "l2")), F.when(F.col("l1") == 0, F.array("m")).otherwise(F.array(first, F.col("m") - first)))


def unique_prefix_design(runs: DataFrame, real: int = 0, hashed: int = 0) -> DataFrame:
    return _design(runs, "unique_prefix", F.array(), F.array(), aux=(real, hashed))


def dyadic_levels(widths: np.ndarray, bits: int, m: int, alloc: str = "last") -> tuple[list[int], list[float]]:
    """Levels of a hierarchical filter for queries of these widths, and their shares of the memory.

    Levels reach up to the largest block a query can hold. ``last`` halves the memory from the last level up, ``equal``
    shares it alike, ``sampled`` gives each level what its share of the sample's blocks asks for, and half to the last.
    """
    count = min(bits, max(1, int(bit_length_numpy(np.maximum(widths, 1)).max(initial=1))))
    lengths = list(range(bits - count + 1, bits + 1))
    if alloc == "equal":
        return lengths, [1 / count] * count
    if alloc == "sampled" and len(widths) and count > 1:
        sizes = bit_length_numpy(np.maximum(widths, 1))
        asked = np.array([float((sizes >= bits - length + 1).sum()) for length in lengths])
        weights = asked[:-1] * 0.5 ** (np.arange(count - 1, 0, -1) / 2)
        return lengths, [*(0.5 * weights / weights.sum()).tolist(), 0.5]
    weights = [2.0**i for i in range(count)]
    return lengths, [w / sum(weights) for w in weights]
