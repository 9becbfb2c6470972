"""Harmonic packing of token ids into sequences of one capacity C.

A document of up to C tokens stays whole where it can; a longer one gives whole sequences of C and a remainder. A length r
belongs to the reciprocal class k = floor(C / r), and a sequence of class k takes k documents, whatever their exact
lengths; lengths below C / ``classes`` share one class that is filled one after another. A sequence that has its number
is full to k/(k+1) or more, and its room is filled to the last token by documents that are cut for that: while room is
open for all tokens of a document, it is dealt out over that room instead of going to its class. Each task fills its own
sequences. Less than one sequence a class is open at any time, and less room than a sequence and one document; what is
open at the end runs into one stream that is cut into sequences of C and then of powers of two, which need no padding.
No shuffle takes place.

Defined results: a null or empty text has its end id alone; repeated rows are packed each; a null doc_id is kept; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from rangegate.llm.text import columns, documents, frugal
from rangegate.llm.tokens import END_ID, default_path, encoder

CAPACITY = 2048
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class HarmonicPacker:
    """Sequences of one worker; pieces are (doc_id, start, ids, doc_tokens)."""

    def __init__(self, capacity: int, first_sequence: int, classes: int = 64):
        self.capacity, self.classes = capacity, classes
        self.next_sequence = first_sequence
        self.open: dict[int, list] = {}
        self.small = 0  # tokens in the shared class of small documents
        self.roomy: deque[tuple[int, list]] = deque()  # sequences with their number of documents: room left, pieces
        self.room = 0
        self.rows: list[tuple] = []

    def _close(self, pieces: list) -> None:
        offset = 0
        for doc_id, start, ids, total in pieces:
            self.rows.append((doc_id, start, len(ids) // 4, ids, total, self.next_sequence, offset))
            offset += len(ids) // 4
        self.next_sequence += 1

    def _complete(self, pieces: list) -> None:
        room = self.capacity - sum(len(p[2]) for p in pieces) // 4
        if room:
            self.roomy.append((room, pieces))
            self.room += room
        else:
            self._close(pieces)

    def _fill(self, piece: tuple) -> None:
        """Deals a piece out over the open room, which is enough for it."""
        doc_id, start, ids, total = piece
        at, length = 0, len(ids) // 4
        self.room -= length
        while at < length:
            room, held = self.roomy.popleft()
            take = min(room, length - at)
            held.append((doc_id, start + at, ids[at * 4 : (at + take) * 4], total))
            at += take
            if take == room:
                self._close(held)
            else:
                self.roomy.appendleft((room - take, held))

    def _put(self, piece: tuple) -> None:
        length = len(piece[2]) // 4
        if length <= self.room:
            self._fill(piece)
            return
        k = self.capacity // length
        if k < self.classes:
            held = self.open.setdefault(k, [])
            held.append(piece)
            if len(held) == k:
                self._complete(self.open.pop(k))
            return
        if self.small + length > self.capacity:
            self._complete(self.open.pop(self.classes))
            self.small = 0
        self.open.setdefault(self.classes, []).append(piece)
        self.small += length

    def add(self, doc_id: int | None, ids: bytes) -> None:
        total, at = len(ids) // 4, 0
        while at < total:
            length = min(self.capacity, total - at)
            self._put((doc_id, at, ids[at * 4 : (at + length) * 4], total))
            at += length

    def finish(self) -> None:
        """Empties the buffers through one stream cut at C and then at powers of two."""
        stream = [p for _, held in self.roomy for p in held] + [p for k in sorted(self.open) for p in self.open[k]]
        self.open, self.small, self.room = {}, 0, 0
        self.roomy.clear()
        left = sum(len(p[2]) for p in stream) // 4
        room, held = 0, []
        for doc_id, start, ids, total in stream:
            at, length = 0, len(ids) // 4
            while at < length:
                room = room or min(self.capacity, 1 << (left.bit_length() - 1))
                take = min(room, length - at)
                held.append((doc_id, start + at, ids[at * 4 : (at + take) * 4], total))
                at, room, left = at + take, room - take, left - take
                if not room:
                    self._close(held)
                    held = []

    def take(self) -> list[tuple]:
        rows, self.rows = self.rows, []
        return rows


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """One row per piece; ``with_ids`` adds the ids as little-endian unsigned 32-bit integers."""

    def out(rows: list[tuple]) -> pa.RecordBatch:
        doc_id, start, length, ids, total, sequence, offset = zip(*rows, strict=True) if rows else ((),) * 7
        crc = [zlib.crc32(x) for x in ids]
        cols = [pa.array(x, pa.int64()) for x in (doc_id, start, length, crc, total, sequence, offset)]
        names = [x.split()[0] for x in PIECES.split(", ")]
        return pa.RecordBatch.from_arrays(cols + [pa.array(ids, pa.binary())] * with_ids, names + ["ids"] * with_ids)

    def run(batches: Iterator) -> Iterator:
        bpe, end = encoder(tokenizer_path), END_ID.to_bytes(4, "little")
        packer = HarmonicPacker(capacity, TaskContext.get().partitionId() << 40)
        for ids, texts in columns(batches, "doc_id", "text"):
            for at in range(0, len(ids), 500):
                for doc_id, encoded in zip(ids[at : at + 500], bpe.encode(texts[at : at + 500]), strict=True):
                    packer.add(doc_id, encoded + end)
                yield out(packer.take())
        packer.finish()
        yield out(packer.take())

    return docs.select("doc_id", "text").mapInArrow(frugal(run), PIECES + ", ids binary" * with_ids)


def op2_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir), default_path())
