"""Helpers shared by the text operators: words, word hashes, rolling hashes, block counts.

Words are the maximal runs of characters other than U+0020 and U+0009 to U+000D. On UTF-8 bytes that is what
``bytes.split()`` returns, and ``bytes.lower()`` folds A-Z only, so both contracts hold without decoding.
"""

from __future__ import annotations

import ctypes
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
#: Odd multiplier of the rolling polynomial hash (fixed value) and its inverse modulo 2^64.
BASE = 0x9E3779B97F4A7C15
BASE_INV = pow(BASE, -1, 1 << 64)


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads all input bits over the output; a bijection of 64-bit integers."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


class Rolling:
    """Rolling polynomial hashes modulo 2^64 of all windows of a sequence, from prefix sums."""

    def __init__(self):
        self.up = self.down = np.ones(1, U64)

    def grow(self, n: int) -> None:
        if len(self.up) < n:
            n = 1 << (n - 1).bit_length()
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.r_[U64(1), np.full(n - 1, BASE, U64)], dtype=U64)
                self.down = np.cumprod(np.r_[U64(1), np.full(n - 1, BASE_INV, U64)], dtype=U64)

    def windows(self, values: np.ndarray, width: int) -> np.ndarray:
        """Mixed hash of every window of ``width`` consecutive values; empty if there are fewer values."""
        n = len(values)
        if n < width:
            return np.empty(0, U64)
        self.grow(n + 1)
        total = np.zeros(n + 1, U64)
        with np.errstate(over="ignore"):
            np.cumsum(values * self.down[:n], out=total[1:])
            return mix64((total[width:] - total[:-width]) * self.up[: n - width + 1] + U64(width))


_BLANK = np.zeros(256, bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True
SPAN = 1 << 20


class WordHasher:
    """64-bit hashes of the words of many texts at once, from prefix sums over their bytes."""

    def __init__(self, fold: bool):
        self.fold, self.rolling = fold, Rolling()

    def of(self, texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words in order, and where each text's words begin and end (one longer than the texts)."""
        data = b" ".join([t or b"" for t in texts])
        data = data.lower() if self.fold else data
        raw = np.frombuffer(data, np.uint8)
        edge = np.flatnonzero(np.diff(np.concatenate(([True], _BLANK[raw], [True])).view(np.int8)))
        starts, ends = edge[::2], edge[1::2]
        out, at = np.empty(len(starts), U64), 0
        while at < len(starts):
            to = max(at + 1, int(np.searchsorted(ends, starts[at] + SPAN, side="right")))
            low, high = int(starts[at]), int(ends[to - 1])
            self.rolling.grow(high - low + 1)
            total = np.zeros(high - low + 1, U64)
            with np.errstate(over="ignore"):
                np.cumsum(raw[low:high] * self.rolling.down[: high - low], out=total[1:])
                s, e = starts[at:to] - low, ends[at:to] - low
                out[at:to] = mix64((total[e] - total[s]) * self.rolling.up[s] + (e - s).astype(U64))
            at = to
        bounds = np.cumsum([0, *(len(t or b"") + 1 for t in texts)])
        return out, np.searchsorted(starts, bounds)

    def each(self, texts: list[bytes | None]) -> Iterator[np.ndarray]:
        """Word hashes text by text; texts are taken together up to about SPAN bytes."""
        at = 0
        while at < len(texts):
            to, size = at, 0
            while to < len(texts) and (to == at or size + len(texts[to] or b"") <= SPAN):
                size += len(texts[to] or b"")
                to += 1
            hashes, bounds = self.of(texts[at:to])
            for i, j in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
                yield hashes[i:j]
            at = to


def distinct(values: np.ndarray) -> np.ndarray:
    """Ascending distinct values; sorts, which is faster here than hashing."""
    if len(values) < 2:
        return values
    values = np.sort(values)
    return values[np.concatenate(([True], values[1:] != values[:-1]))]


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every window of ``width`` values by doubling."""
    out, have = values, 1
    while have * 2 <= width:
        out, have = np.minimum(out[:-have], out[have:]), have * 2
    return out if have == width else np.minimum(out[: len(out) - (width - have)], out[width - have :])


def in_sorted(values: np.ndarray, ascending: np.ndarray) -> np.ndarray:
    """Which values are in an ascending array; costs its logarithm a value, not its length a call."""
    if not len(ascending):
        return np.zeros(len(values), bool)
    at = np.searchsorted(ascending, values)
    return ascending[np.minimum(at, len(ascending) - 1)] == values


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def text_bytes(docs: DataFrame, *others: str) -> DataFrame:
    """doc_id, the named columns, and text as UTF-8 bytes; nothing else is read."""
    return docs.select("doc_id", *others, F.col("text").cast("binary").alias("text"))


def blocks_for(docs: DataFrame, block_bytes: int) -> int:
    """Number of blocks of about ``block_bytes`` of text each."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(1, math.ceil(total / block_bytes))


def with_block(docs: DataFrame, blocks: int) -> DataFrame:
    return docs.withColumn("blk", F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def give_back() -> None:
    """Memory that is free goes back to the system, where the C library can do that."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def frugal(run: Callable) -> Callable:
    """``run`` of batches, of a group or of a cogroup, after which free memory goes back; a worker that waits for its next task
    would keep it beside the heap of its executor."""

    def batches(given):
        yield from run(given)
        give_back()

    def group(key, table):
        out = run(key, table)
        give_back()
        return out

    def cogroup(key, left, right):
        out = run(key, left, right)
        give_back()
        return out

    return (batches, group, cogroup)[run.__code__.co_argcount - 1]


def columns(batches: Iterator, *names: str, rows: int = 1000) -> Iterator[tuple[list, ...]]:
    """Python lists of the named columns, at most ``rows`` rows at a time, so that few texts are held twice."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            part = batch.slice(at, rows)
            yield tuple(part.column(n).to_pylist() for n in names)
