"""Exact deduplication by a cuckoo-filter index of live digests.

Every text is reduced to the SHA-256 of its A-Z-folded UTF-8 bytes. Each task sends a digest once, with its largest doc_id
and its rows; digests are dealt to buckets of bounded size. A bucket's index takes these rows one by one: a cuckoo filter
of short fingerprints proves most digests new; a hit is verified against the digests stored in the bucket, and may be
false. Copies of other tasks meet here: where a row with a larger id takes over a text, the live entry is deleted
and inserted anew. A filter starts small; when it cannot place an entry it is built again twice as large from the stored
digests. What the index holds at the end decides which rows stay.

Defined results: a null text counts as empty; repeated doc_ids count as separate rows, so of equal texts all rows with the
largest doc_id read as kept; a null doc_id stays only if no other copy has an id; an empty table gives an empty
result; other columns are ignored. A text that a third of all rows share sends one row per task. Digests of 256 bits
stand for the texts.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.llm.graph import stored
from rangegate.llm.text import columns, documents, text_bytes

SLOTS = 4
MAX_KICKS = 200
NO_ID = -(1 << 63)


class CuckooFilter:
    """Approximate set of digests with insert, delete and lookup; ``insert`` is False when it overflows.

    ``digest`` is any bytes of at least 12; an entry is a 16-bit fingerprint in one of two buckets of four slots.
    """

    def __init__(self, capacity: int):
        self.buckets = 1 << max(1, math.ceil(math.log2(max(1, capacity) / (SLOTS * 0.9))))
        self.table = [0] * (self.buckets * SLOTS)
        self.size = 0

    def _places(self, digest: bytes) -> tuple[int, int, int]:
        fingerprint = int.from_bytes(digest[:2], "little") or 1
        first = int.from_bytes(digest[2:10], "little") & (self.buckets - 1)
        return fingerprint, first, self._other(first, fingerprint)

    def _other(self, bucket: int, fingerprint: int) -> int:
        return (bucket ^ (fingerprint * 0x5BD1E995)) & (self.buckets - 1)

    def _find(self, bucket: int, fingerprint: int) -> int:
        try:
            return self.table.index(fingerprint, bucket * SLOTS, bucket * SLOTS + SLOTS)
        except ValueError:
            return -1

    def __contains__(self, digest: bytes) -> bool:
        fingerprint, a, b = self._places(digest)
        return self._find(a, fingerprint) >= 0 or self._find(b, fingerprint) >= 0

    def insert(self, digest: bytes) -> bool:
        fingerprint, a, b = self._places(digest)
        for bucket in (a, b):
            if (at := self._find(bucket, 0)) >= 0:
                self.table[at] = fingerprint
                self.size += 1
                return True
        bucket = b
        for kick in range(MAX_KICKS):
            at = bucket * SLOTS + (kick + fingerprint) % SLOTS
            fingerprint, self.table[at] = self.table[at], fingerprint
            bucket = self._other(bucket, fingerprint)
            if (at := self._find(bucket, 0)) >= 0:
                self.table[at] = fingerprint
                self.size += 1
                return True
        return False

    def delete(self, digest: bytes) -> bool:
        """Only digests that were inserted may be deleted."""
        fingerprint, a, b = self._places(digest)
        for bucket in (a, b):
            if (at := self._find(bucket, fingerprint)) >= 0:
                self.table[at] = 0
                self.size -= 1
                return True
        return False


class DigestIndex:
    """Exact index: the filter answers misses, stored digests verify hits and feed a resize."""

    def __init__(self, capacity: int = 1024):
        self.filter = CuckooFilter(capacity)
        self.live: dict[bytes, tuple[int, int]] = {}
        self.misses = self.hits = self.false_hits = self.deletions = self.resizes = 0

    def _insert(self, digest: bytes, owner: int, rows: int) -> None:
        self.live[digest] = (owner, rows)
        if not self.filter.insert(digest):
            capacity = self.filter.buckets * SLOTS
            while True:
                capacity *= 2
                self.resizes += 1
                self.filter = CuckooFilter(capacity)
                if all(self.filter.insert(d) for d in self.live):
                    return

    def add(self, digest: bytes, owner: int, rows: int = 1) -> None:
        """Rows of a text whose largest id is ``owner``."""
        known = None
        if digest in self.filter:
            known = self.live.get(digest)
            self.hits += known is not None
            self.false_hits += known is None
        else:
            self.misses += 1
        if known is None:
            self._insert(digest, owner, rows)
        elif owner > known[0]:
            self.remove(digest)
            self._insert(digest, owner, rows + known[1])
        else:
            self.live[digest] = (known[0], rows + known[1])

    def remove(self, digest: bytes) -> bool:
        if digest in self.filter and digest in self.live:
            self.filter.delete(digest)
            del self.live[digest]
            self.deletions += 1
            return True
        return False


def fold(text: bytes | None) -> bytes:
    return hashlib.sha256((text or b"").lower()).digest()


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, digest of every row."""

    def run(batches: Iterator) -> Iterator:
        for ids, texts in columns(batches, "doc_id", "text"):
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([fold(t) for t in texts], pa.binary())], ["doc_id", "digest"])

    return text_bytes(docs).mapInArrow(run, "doc_id long, digest binary")


def _once_a_task(rows: DataFrame, limit: int = 500_000) -> DataFrame:
    """digest, owner, n: rows of one digest combined while a task holds at most ``limit`` digests."""

    def run(batches: Iterator) -> Iterator:
        held: dict[bytes, tuple[int, int]] = {}

        def out() -> pa.RecordBatch:
            owner, n = zip(*held.values(), strict=True) if held else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(owner, pa.int64()), pa.array(n, pa.int64())], ["digest", "owner", "n"])

        for ids, found in columns(batches, "doc_id", "digest", rows=10_000):
            for doc_id, digest in zip(ids, found, strict=True):
                owner, n = held.get(digest, (NO_ID, 0))
                held[digest] = (owner if doc_id is None else max(owner, doc_id), n + 1)
            if len(held) >= limit:
                yield out()
                held.clear()
        yield out()

    return rows.mapInArrow(run, "digest binary, owner long, n long")


def live_digests(rows: DataFrame, n_rows: int, bucket_rows: int = 100_000, capacity: int = 1024) -> tuple[DataFrame, DataFrame]:
    """digest, keep_id, group_size of each text; and bucket, misses, hits, false_hits, deletions, resizes of each index.

    Buckets take about ``bucket_rows`` digests; ``capacity`` is that of a new filter.
    """
    buckets = max(1, math.ceil(n_rows / bucket_rows))

    def run(key, table):
        index = DigestIndex(capacity)
        for digest, owner, n in zip(*(table.column(c).to_pylist() for c in ("digest", "owner", "n")), strict=True):
            index.add(digest, owner, n)
        keep, sizes = zip(*index.live.values(), strict=True)
        none, counters = [None] * len(keep), [index.misses, index.hits, index.false_hits, index.deletions, index.resizes]
        return pa.table({"bucket": pa.array([*none, key[0].as_py()], pa.int64()), "digest": pa.array([*index.live, None], pa.binary()), "keep_id": pa.array([*keep, None], pa.int64()), "group_size": pa.array([*sizes, None], pa.int64()), "counters": pa.array([*none, counters], pa.list_(pa.int64()))})

    bucketed = _once_a_task(rows).withColumn("bucket", F.pmod(F.xxhash64("digest"), F.lit(buckets)))
    out = stored(bucketed.groupBy("bucket").applyInArrow(run, "bucket long, digest binary, keep_id long, group_size long, counters array<long>"))
    names = ("misses", "hits", "false_hits", "deletions", "resizes")
    return out.where("digest is not null").select("digest", "keep_id", "group_size"), out.where("digest is null").select("bucket", *[F.col("counters")[i].alias(c) for i, c in enumerate(names)])


def exact_dedup(docs: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = stored(digests(docs))
    live, _ = live_digests(rows, rows.count(), **options)
    joined = rows.join(live, "digest").withColumn("keep_id", F.nullif("keep_id", F.lit(NO_ID)))
    return joined.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def op8_cuckoo_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(documents(spark, sf_dir))


OP8_SQL = """
with d as (
  select doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) as h from documents
), g as (select h, max(doc_id) as keep_id, count(*) as group_size from d group by h)
select d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id as kept, d.h as text_sha256 from d join g using (h)
"""
