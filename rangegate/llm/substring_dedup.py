"""Removal of repeated passages: every window of W consecutive words that occurs elsewhere is taken out.

Rabin-Karp hashes of all windows come from one pass of prefix sums per document and are counted in Spark; repeated windows
merge into maximal removal intervals. To keep the count small, each window also has an anchor: the smallest hash of
the q-word grams inside it. Equal windows have equal anchors, so a window whose anchor gram stands at one place only in
the whole corpus is proven unique and its hash need not travel. Counts are combined per block of documents first, so a
passage that a third of all rows share sends one row per block.

A window is judged by its 64-bit hash together with its 64-bit anchor, both functions of the word sequence. Defined
results: null and empty texts have no words; documents shorter than W words lose nothing; a repeated doc_id is one more
document; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangegate.llm.text import Rolling, WordHasher, blocks_for, columns, distinct, documents, in_sorted, signed, sliding_min, text_bytes, with_block

WINDOW_WORDS = 35
GRAM_WORDS = 8
BLOCK_BYTES = 8 << 20


class Windows:
    """Window hashes and anchors of documents."""

    def __init__(self, width: int, gram: int):
        self.width, self.gram = width, gram
        self.hasher, self.rolling = WordHasher(fold=False), Rolling()

    def each(self, texts: list[bytes | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """For each text, per window its hash and its anchor, and per q-gram its hash."""
        none = np.empty(0, np.uint64)
        for x in self.hasher.each(texts):
            if len(x) < self.width:
                yield none, none, none
            else:
                grams = self.rolling.windows(x, self.gram)
                yield self.rolling.windows(x, self.width), sliding_min(grams, self.width - self.gram + 1), grams


def _counted(values: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(np.concatenate(values), return_counts=True) if values else (np.empty(0, np.uint64), np.empty(0, np.int64))


def _anchor_counts(docs: DataFrame, width: int, gram: int) -> DataFrame:
    """blk, anchor, n: at how many places of the block the anchor's gram is the smallest of some window."""

    def run(batches: Iterator) -> Iterator:
        windows = Windows(width, gram)
        for blocks, texts in columns(batches, "blk", "text"):
            found: dict[int, list[np.ndarray]] = {}
            for blk, (_, anchors, grams) in zip(blocks, windows.each(texts), strict=True):
                if len(anchors):
                    found.setdefault(blk, []).append(grams[in_sorted(grams, distinct(anchors))])
            for blk, values in found.items():
                anchors, n = _counted(values)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), blk, np.int32)), pa.array(signed(anchors)), pa.array(n.astype(np.int32))], ["blk", "anchor", "n"])

    return docs.select("blk", "text").mapInArrow(run, "blk int, anchor long, n int")


def _repeated(counts: DataFrame, *keys: str) -> DataFrame:
    """Rows of keys that are counted twice or more over all blocks."""
    return counts.withColumn("total", F.sum("n").over(Window.partitionBy(*keys))).where("total > 1").drop("total")


def _window_counts(docs: DataFrame, anchors: DataFrame, width: int, gram: int) -> DataFrame:
    """blk, h, anchor, n of all windows whose anchor is in the block's list.

    Takes the same columns as the last step, so that both read one exchange of the texts.
    """

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        windows = Windows(width, gram)
        wanted = distinct(right.column("anchor").to_numpy().view(np.uint64))
        hashes, places = [], []
        for h, a, _ in windows.each(left.column("text").to_pylist()) if len(wanted) else []:
            hit = in_sorted(a, wanted)
            hashes.append(h[hit])
            places.append(a[hit])
        hashes, first, n = np.unique(np.concatenate(hashes or [wanted[:0]]), return_index=True, return_counts=True)
        return pa.table({"blk": pa.array(np.full(len(n), key[0].as_py(), np.int32)), "h": pa.array(signed(hashes)), "anchor": pa.array(signed(np.concatenate(places or [wanted[:0]])[first])), "n": pa.array(n.astype(np.int32))})

    return docs.groupBy("blk").cogroup(anchors.select("blk", "anchor").groupBy("blk")).applyInArrow(run, "blk int, h long, anchor long, n int")


def covered_words(hit: np.ndarray, n_words: int, width: int) -> np.ndarray:
    """Boolean per word: inside one of the windows that start where ``hit`` is set (intervals merge)."""
    at = np.flatnonzero(hit)
    if not len(at):
        return np.zeros(n_words, bool)
    edge = np.zeros(n_words + 1, np.int64)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + width, -1)
    return np.cumsum(edge[:-1]) > 0


def repeated_passages(docs: DataFrame, width: int = WINDOW_WORDS, gram: int = GRAM_WORDS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, kept text, removal intervals [start, end) in words, one row per document."""
    dealt = with_block(text_bytes(docs), blocks_for(docs, block_bytes))
    anchors = _repeated(_anchor_counts(dealt, width, gram), "anchor")
    repeated = _repeated(_window_counts(dealt, anchors, width, gram), "h", "anchor")

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        windows = Windows(width, gram)
        bad = distinct(right.column("h").to_numpy().view(np.uint64))
        n_words, kept, starts, ends = [], [], [], []
        texts = left.column("text").to_pylist()
        for text, (hashes, _, _) in zip(texts, windows.each(texts), strict=True):
            words = (text or b"").split()
            gone = covered_words(in_sorted(hashes, bad), len(words), width)
            step = np.diff(np.r_[False, gone, False].astype(np.int8))
            starts.append(np.flatnonzero(step == 1).tolist())
            ends.append(np.flatnonzero(step == -1).tolist())
            n_words.append(len(words))
            kept.append(b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g] if starts[-1] else words))
        return pa.table({"doc_id": left.column("doc_id"), "n_words": pa.array(n_words, pa.int64()), "kept": pa.array(kept, pa.binary()), "starts": pa.array(starts, pa.list_(pa.int32())), "ends": pa.array(ends, pa.list_(pa.int32()))})

    return dealt.groupBy("blk").cogroup(repeated.select("blk", "h").groupBy("blk")).applyInArrow(run, "doc_id long, n_words long, kept binary, starts array<int>, ends array<int>")


def op9_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = repeated_passages(documents(spark, sf_dir))
    removed = F.aggregate(F.zip_with("starts", "ends", lambda a, b: (b - a).cast("long")), F.lit(0).cast("long"), lambda s, x: s + x)
    return out.select("doc_id", "n_words", removed.alias("n_removed"), F.sha2("kept", 256).alias("kept_sha256"))


OP9_SQL = """
with w as (
  select doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as ws from documents
), win as (
  select doc_id, i, array_to_string(ws[i:i+34], ' ') as s from w, unnest(range(1, len(ws) - 33)) as t(i)
), bad as (
  select doc_id, i from (select doc_id, i, count(*) over (partition by md5(s)) as c from win) where c > 1
), gone as (
  select distinct doc_id, i + k as p from bad, range(0, 35) as r(k)
), cut as (
  select doc_id, list(p) as ps from gone group by doc_id
)
select w.doc_id, len(ws)::bigint as n_words, coalesce(len(ps), 0)::bigint as n_removed,
  sha256(array_to_string(case when ps is null then ws else list_filter(ws, lambda x, j: not list_contains(ps, j)) end, ' ')) as kept_sha256
from w left join cut using (doc_id)
"""
