"""Uniform-depth trie of prefixes in level order: bitmaps for the top byte levels, label lists with first-in-node bits below.

``encode_tails`` ends a branch where one prefix is left of it and keeps the rest of that prefix as raw bits.
"""

from __future__ import annotations

import numpy as np

from rangegate.operators.search import RANK_OVERHEAD

HEAD = 24
#: Elements that are worked on at a time, a multiple of 8.
PART = 1 << 15


def _levels(depth: int) -> list[tuple[int, int]]:
    return [(s, min(s + 8, depth)) for s in range(0, depth, 8)]


def _parts(n: int, size: int = PART) -> list[slice]:
    return [slice(a, min(a + size, n)) for a in range(0, n, size)]


def starts(ascending: np.ndarray, shift: int) -> np.ndarray:
    """Which numbers differ from the one before, without their last ``shift`` bits."""
    new = np.ones(len(ascending), bool)
    for x in _parts(len(ascending) - 1):
        new[x.start + 1 : x.stop + 1] = (ascending[x] ^ ascending[x.start + 1 : x.stop + 1]) >> shift != 0
    return new


def _level_body(ends: np.ndarray, width: int, dense: bool) -> bytes:
    """One level of nodes, ``ends`` being their sorted prefixes."""
    first, node = starts(ends, width), -1
    label = np.empty(0 if dense else len(ends), np.uint8)
    bitmap = np.zeros((int(first.sum()) if dense else 0, 1 << width), bool)
    for x in _parts(len(ends)):
        own = ends[x] & ((1 << width) - 1)
        if dense:
            nodes = node + np.cumsum(first[x])
            bitmap[nodes, own] = True
            node = int(nodes[-1])
        else:
            label[x] = own
    return np.packbits(bitmap).tobytes() if dense else np.packbits(first).tobytes() + label.tobytes()


def _read_level(blob: bytes, at: int, nodes: np.ndarray, width: int, count: int, dense: bool) -> tuple[np.ndarray, int]:
    """Prefixes of a level below ``nodes``, and where its bytes end."""
    out, done, parent = np.empty(count, np.int64), 0, -1
    if dense:
        size = (len(nodes) << width) + 7 >> 3
        bitmap = np.unpackbits(np.frombuffer(blob, np.uint8, size, at))
        for x in _parts(len(nodes), PART >> width):
            found = np.flatnonzero(bitmap[x.start << width : x.stop << width])
            out[done : done + len(found)] = (nodes[x][found >> width] << width) | (found & ((1 << width) - 1))
            done += len(found)
        return out, at + size
    first, label = np.unpackbits(np.frombuffer(blob, np.uint8, count + 7 >> 3, at)), np.frombuffer(blob, np.uint8, count, at + (count + 7 >> 3))
    for x in _parts(count):
        parents = parent + np.cumsum(first[x], dtype=np.int64)
        out[x] = (nodes[parents] << width) | label[x]
        parent = int(parents[-1])
    return out, at + (count + 7 >> 3) + count


def encode(prefixes: np.ndarray, depth: int, dense_levels: int) -> bytes:
    """Blob of sorted distinct prefixes of ``depth`` bits."""
    out = [np.array([depth, dense_levels, len(prefixes)], "<i8").tobytes()]
    for j, (s, e) in enumerate(_levels(depth)):
        ends = np.unique(prefixes >> (depth - e))
        out.append(np.array([len(ends)], "<i8").tobytes() + _level_body(ends, e - s, j < dense_levels))
    return b"".join(out)


def decode(blob: bytes) -> np.ndarray:
    """The prefixes of a blob."""
    depth, dense_levels, n = np.frombuffer(blob, "<i8", 3).tolist()
    at, nodes = HEAD, np.zeros(1 if n else 0, np.int64)
    for j, (s, e) in enumerate(_levels(depth)):
        count, at = int(np.frombuffer(blob, "<i8", 1, at)[0]), at + 8
        nodes, at = _read_level(blob, at, nodes, e - s, count, j < dense_levels)
    return nodes


def exact_bits(prefixes: np.ndarray, depth: int, dense_levels: int) -> int:
    """Bits of the level-order structures with their rank directory, without the header."""
    total = 0
    for j, (s, e) in enumerate(_levels(depth)):
        ends = np.unique(prefixes >> (depth - e))
        total += len(np.unique(ends >> (e - s))) << (e - s) if j < dense_levels else len(ends) * (e - s + 1)
    return int(np.ceil(total * (1 + RANK_OVERHEAD)))


def _pack_bits(values: np.ndarray, width: int) -> bytes:
    places = np.arange(width - 1, -1, -1)
    return b"".join(np.packbits((values[x, None] >> places) & 1).tobytes() for x in _parts(len(values)))


def _unpack_bits(blob: bytes, at: int, count: int, width: int) -> np.ndarray:
    out, weights = np.empty(count, np.int64), np.int64(1) << np.arange(width - 1, -1, -1)
    for x in _parts(count):
        n = x.stop - x.start
        out[x] = np.unpackbits(np.frombuffer(blob, np.uint8, n * width + 7 >> 3, at + x.start * width // 8))[: n * width].reshape(n, width).astype(np.int64) @ weights
    return out


def encode_tails(prefixes: np.ndarray, depth: int, dense_levels: int) -> bytes:
    """Blob of sorted distinct prefixes whose single-prefix branches are cut and end in raw bits."""
    out, live = [np.array([depth, dense_levels, len(prefixes)], "<i8").tobytes()], prefixes
    del prefixes  # a caller that holds no other name frees them with the first level
    for j, (s, e) in enumerate(_levels(depth)):
        new, below = starts(live, depth - e), depth - e
        lone = new & np.r_[new, True][1:] if below else np.zeros(len(live), bool)
        tails, ends = live[lone] & ((1 << below) - 1), live[new] >> below if below else live
        out.append(np.array([len(ends), len(tails)], "<i8").tobytes() + _level_body(ends, e - s, j < dense_levels))
        del ends
        if below:
            out.append(np.packbits(lone[new]).tobytes() + _pack_bits(tails, below))
            live = live[~lone]
    return b"".join(out)


def decode_tails(blob: bytes) -> np.ndarray:
    """The sorted prefixes of a blob with tails."""
    depth, dense_levels, n = np.frombuffer(blob, "<i8", 3).tolist()
    at, nodes, found = HEAD, np.zeros(1 if n else 0, np.int64), []
    for j, (s, e) in enumerate(_levels(depth)):
        (count, cuts), at = np.frombuffer(blob, "<i8", 2, at).tolist(), at + 16
        nodes, at = _read_level(blob, at, nodes, e - s, count, j < dense_levels)
        if e < depth:
            cut = np.unpackbits(np.frombuffer(blob, np.uint8, count + 7 >> 3, at))[:count].astype(bool)
            at += count + 7 >> 3
            if cuts:
                found.append((nodes[cut] << (depth - e)) | _unpack_bits(blob, at, cuts, depth - e))
                nodes = nodes[~cut]
            at += cuts * (depth - e) + 7 >> 3
    if found:
        nodes = np.concatenate([*found, nodes])
        nodes.sort()
    return nodes


def stored_bits(blob: bytes) -> int:
    """Bits of a stored trie with the rank directory that a walk over it needs; the header is not counted."""
    return int(np.ceil(8 * max(0, len(blob) - HEAD) * (1 + RANK_OVERHEAD)))
