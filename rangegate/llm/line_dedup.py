"""Line deduplication by overlapping windows of three consecutive lines.

Lines without a word are passed over; the others are compared without the blanks at their ends. Every window of three
such lines is hashed (128 bits); of the windows with one hash the first by (doc_id, position) stays, the lines of all
later ones are covered, and covered positions merge into what is removed. A row is known by its id and the hash of its
text, so rows that share an id, or have none, keep their own positions.

Defined results: null texts, empty texts and texts of fewer than three lines keep everything; equal rows of one id stay
together, different texts of one id come in the order of their hashes; rows with a null doc_id come last; an empty table gives an
empty result; other columns are kept as they are. The first window of a hash is a grouped minimum combined in each task,
and only hashes seen twice are joined back, so a block of lines in a third of all rows is split like any skewed key.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.llm.text import columns, documents, frugal

WINDOW_LINES = 3
LAST = (1 << 63) - 1


def line_windows(docs: DataFrame, width: int = WINDOW_LINES) -> DataFrame:
    """h, doc_id, own (hash of the text), at: every window of ``width`` lines with a word and the number of its first line among these."""

    def run(batches: Iterator) -> Iterator:
        for ids, own, texts in columns(batches, "doc_id", "own", "text"):
            hashes, owners, marks, places = [], [], [], []
            for doc_id, mark, text in zip(ids, own, texts, strict=True):
                lines = [x for line in (text or b"").split(b"\n") if (x := line.strip())]
                for at in range(len(lines) - width + 1):
                    hashes.append(xxhash.xxh3_128_digest(b"\n".join(lines[at : at + width])))
                    owners.append(LAST if doc_id is None else doc_id)
                    marks.append(mark)
                    places.append(at)
            yield pa.RecordBatch.from_arrays([pa.array(hashes, pa.binary()), pa.array(owners, pa.int64()), pa.array(marks, pa.int64()), pa.array(places, pa.int32())], ["h", "doc_id", "own", "at"])

    own = F.xxhash64("text").alias("own")
    return docs.select("doc_id", own, F.col("text").cast("binary").alias("text")).mapInArrow(frugal(run), "h binary, doc_id long, own long, at int")


def later_windows(windows: DataFrame) -> DataFrame:
    """doc_id, own, starts: the windows of each row that stand somewhere before."""
    first = windows.groupBy("h").agg(F.min(F.struct("doc_id", "own", "at")).alias("first"), F.count("*").alias("n")).where("n > 1")
    later = windows.join(first.select("h", "first"), "h").where("doc_id <> first.doc_id or own <> first.own or at <> first.at")
    return later.groupBy("doc_id", "own").agg(F.collect_set("at").alias("starts"))


def without_lines(text: str, starts: list[int], width: int = WINDOW_LINES) -> tuple[str, int, int]:
    """The text without the covered lines, its number of lines with a word, and how many of them went."""
    gone = {p for s in starts for p in range(s, s + width)}
    kept, at, removed = [], 0, 0
    for line in text.split("\n"):
        if line.strip(" \t\n\r\x0b\x0c"):
            if at in gone:
                removed += 1
            else:
                kept.append(line)
            at += 1
        else:
            kept.append(line)
    return "\n".join(kept), at, removed


def with_starts(docs: DataFrame, width: int = WINDOW_LINES) -> DataFrame:
    """``docs`` with a column ``starts__``: null, or the windows to take out."""
    later = later_windows(line_windows(docs, width)).select(F.col("doc_id").alias("id__"), F.col("own").alias("own__"), F.col("starts").alias("starts__"))
    same = (F.coalesce(docs["doc_id"], F.lit(LAST)) == F.col("id__")) & (F.xxhash64(docs["text"]) == F.col("own__"))
    return docs.join(later, same, "left").drop("id__", "own__")


def dedup_lines(docs: DataFrame, width: int = WINDOW_LINES, drop_emptied: bool = True) -> DataFrame:
    """``docs`` with repeated lines taken out of ``text``; ``n_chars`` follows where it exists.

    Documents that lose their last line with a word go, unless ``drop_emptied`` is false.
    """
    names = docs.columns

    def run(batches: Iterator) -> Iterator:
        for batch in batches:
            texts, keep = batch.column("text").to_pylist(), []
            for i, starts in enumerate(batch.column("starts__").to_pylist()):
                lines = removed = 0
                if starts and texts[i] is not None:
                    texts[i], lines, removed = without_lines(texts[i], starts, width)
                keep.append(not drop_emptied or not removed or removed < lines)
            arrays = {n: batch.column(n) for n in names} | {"text": pa.array(texts, batch.schema.field("text").type)}
            if "n_chars" in names:
                chars = [None if t is None else len(t) if s else c for t, s, c in zip(texts, batch.column("starts__").to_pylist(), batch.column("n_chars").to_pylist(), strict=True)]
                arrays["n_chars"] = pa.array(chars, batch.schema.field("n_chars").type)
            yield pa.RecordBatch.from_arrays([arrays[n] for n in names], names).filter(pa.array(keep, pa.bool_()))

    return with_starts(docs, width).mapInArrow(frugal(run), docs.schema)


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_lines (with a word), n_removed, kept_sha256 of every document."""

    def run(batches: Iterator) -> Iterator:
        import hashlib

        for ids, texts, starts in columns(batches, "doc_id", "text", "starts__"):
            out = [without_lines(t or "", s or []) for t, s in zip(texts, starts, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([o[1] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.int64()), pa.array([hashlib.sha256(o[0].encode()).hexdigest() for o in out])], ["doc_id", "n_lines", "n_removed", "kept_sha256"])

    return with_starts(documents(spark, sf_dir).select("doc_id", "text")).mapInArrow(run, "doc_id long, n_lines long, n_removed long, kept_sha256 string")


OP10_SQL = """
with l as (
  select doc_id, i, line, trim(line, chr(32) || chr(9) || chr(11) || chr(12) || chr(13)) as x
  from (select doc_id, string_split(coalesce(text, ''), chr(10)) as ls from documents), unnest(ls) with ordinality as u(line, i)
), n as (
  select *, row_number() over (partition by doc_id order by i) - 1 as p from l where x <> ''
), w as (
  select doc_id, p, x || chr(10) || lead(x, 1) over d || chr(10) || lead(x, 2) over d as k from n window d as (partition by doc_id order by i)
), later as (
  select doc_id, p from (select doc_id, p, row_number() over (partition by k order by doc_id, p) as r from w where k is not null) where r > 1
), gone as (
  select distinct doc_id, p + j as p from later, range(0, 3) as t(j)
), c as (
  select n.doc_id, n.i from n join gone using (doc_id, p)
), agg as (
  select l.doc_id, count(*) filter (where x <> '') as n_lines, count(c.i) as n_removed,
    coalesce(string_agg(l.line, chr(10) order by l.i) filter (where c.i is null), '') as kept
  from l left join c using (doc_id, i) group by l.doc_id
)
select doc_id, n_lines::bigint as n_lines, n_removed::bigint as n_removed, sha256(kept) as kept_sha256 from agg
"""
