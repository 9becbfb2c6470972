"""Counts, over all blocks, of the 64-bit keys that each block holds.

Documents are dealt to blocks of bounded size. A block sends the sorted distinct keys it holds, cut by the upper bits of
the keys into slices, one row a slice; a group of slices with one range of keys adds them up and answers each slice with
the totals of its keys in their order. So a key costs its differences to its neighbours on the way, and one number back;
a key of a third of all rows is one key a block. Nothing is broadcast or collected, whatever the number of keys.

Keys may be cut to their leading bits, as many as the number of tokens needs and some to spare: totals are then those of
all keys with these bits, never too low, and too high for one key in 2^spare.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np

U64 = np.uint64


def pack(values: np.ndarray) -> bytes:
    """Compressed byte planes: bytes of one place stand together, so small numbers cost little."""
    return zlib.compress(np.ascontiguousarray(values).view(np.uint8).reshape(len(values), values.itemsize).T.tobytes(), 1)


def unpack(data: bytes, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    planes = np.frombuffer(zlib.decompress(data), np.uint8).reshape(size, -1)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def key_bits(blocks: int, block_bytes: int, spare: int) -> int:
    """Leading bits that keep a key of each token apart, and ``spare`` more; a token takes two bytes at least."""
    return min(64, spare + max(1, blocks * block_bytes // 2).bit_length())


def cut(keys: np.ndarray, bits: int) -> np.ndarray:
    """Keys with all but their leading bits zero; the order stays."""
    return (keys >> U64(64 - bits)) << U64(64 - bits)


def pack_keys(ascending: np.ndarray, bits: int) -> bytes:
    return pack(np.diff(ascending >> U64(64 - bits), prepend=U64(0)))


def unpack_keys(data: bytes, bits: int) -> np.ndarray:
    return np.cumsum(unpack(data, "<u8"), dtype=U64) << U64(64 - bits)


def slices(ascending: np.ndarray, parts: int) -> Iterator[tuple[int, int, int]]:
    """part, begin and end of the keys of each part that has some; the part rises with the key."""
    part = ((ascending >> U64(32)) * U64(parts)) >> U64(32)
    cuts = np.flatnonzero(np.diff(part)) + 1
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(ascending)], strict=True):
        if b > a:
            yield int(part[a]), a, b


def totals(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Distinct keys, their totals, and the totals of each slice's keys."""
    distinct, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.bincount(inverse, np.concatenate(counts), len(distinct)).astype(np.int64)
    ends = np.cumsum([len(k) for k in keys])
    return distinct, total, [total[inverse[e - len(k) : e]] for e, k in zip(ends.tolist(), keys, strict=True)]
