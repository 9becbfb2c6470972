"""Training-order materialisation of token ids.

Documents' ids run into sequences of a fixed number of tokens; each task fills its own and pads its last one with id 0.
The sequences are written once, so their numbers hold. A keyed Feistel network over the next even power of two,
walked along its cycle until the value is below the number of sequences, permutes their numbers: the result is the slot
of a sequence in training order. On disk and between tasks ids travel compressed. Range partitions of slots hold whole shards of a fixed number of slots of fixed width,
so slot s starts at byte (s mod shard_slots) * stride of shard s div shard_slots, and a reader may resume anywhere.

Defined results: a null or empty text has its end id alone; repeated rows are taken each; a null doc_id is kept; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import os
import uuid
import zlib
from collections.abc import Iterator
from functools import cache
from urllib.parse import urlparse

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangegate.llm.graph import checkpoints, stored
from rangegate.llm.text import columns, documents, mix64
from rangegate.llm.tokens import END_ID, default_path, encoder

SEQUENCE_TOKENS = 2048
SHARD_SLOTS = 4096
KEY = 0x5DEECE66D
ROUNDS = 6
PIECE = "array<struct<doc_id:long,start:long,length:int>>"


def squeezed(ids: bytes) -> bytes:
    return _codec().compress(ids, asbytes=True)


def restored(data: bytes, width: int) -> bytes:
    return _codec().decompress(data, decompressed_size=2 * width, asbytes=True)


@cache
def _codec() -> pa.Codec:
    return pa.Codec("zstd", 3)


def feistel(x: np.ndarray, n: int, key: int = KEY, inverse: bool = False) -> np.ndarray:
    """Keyed permutation of 0 .. n-1 (or its inverse), by cycle-walking over the next power of four."""
    if n <= 1:
        return np.zeros_like(x)
    half = max(1, -(-(n - 1).bit_length() // 2))
    mask, shift = np.uint64((1 << half) - 1), np.uint64(half)

    def once(v: np.ndarray) -> np.ndarray:
        left, right = v >> shift, v & mask
        with np.errstate(over="ignore"):
            for r in range(ROUNDS)[:: -1 if inverse else 1]:
                salt = np.uint64((key * 2 + 1) * (r + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
                if inverse:
                    left, right = right ^ (mix64(left + salt) & mask), left
                else:
                    left, right = right, left ^ (mix64(right + salt) & mask)
        return (left << shift) | right

    out = once(x.astype(np.uint64))
    while (far := out >= np.uint64(n)).any():
        out[far] = once(out[far])
    return out.astype(np.int64)


def sequences(docs: DataFrame, tokenizer_path: str, width: int = SEQUENCE_TOKENS) -> DataFrame:
    """part, idx, n_tokens, pieces, packed: the compressed ids (unsigned 16-bit, little-endian, padded to ``width``)."""

    def run(batches: Iterator) -> Iterator:
        bpe, end, part = encoder(tokenizer_path), END_ID.to_bytes(4, "little"), TaskContext.get().partitionId()
        held, pieces, rows, made = [], [], [], 0
        size = 0

        def close() -> None:
            nonlocal held, pieces, size, made
            ids = np.zeros(width, "<u2")
            given = np.frombuffer(b"".join(held), "<u4")
            if given.max() > 0xFFFF:
                raise ValueError(f"id {given.max()} does not fit 16 bits")
            ids[:size] = given
            rows.append((made, size, pieces, squeezed(ids.tobytes())))
            held, pieces, size, made = [], [], 0, made + 1

        def out() -> pa.RecordBatch:
            idx, n, where, ids = zip(*rows, strict=True) if rows else ((),) * 4
            kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int32())]))
            batch = pa.RecordBatch.from_arrays([pa.array([part] * len(idx), pa.int32()), pa.array(idx, pa.int64()), pa.array(n, pa.int32()), pa.array(where, kind), pa.array(ids, pa.binary())], ["part", "idx", "n_tokens", "pieces", "packed"])
            rows.clear()
            return batch

        for doc_ids, texts in columns(batches, "doc_id", "text"):
            for at in range(0, len(doc_ids), 500):
                for doc_id, ids in zip(doc_ids[at : at + 500], bpe.encode(texts[at : at + 500]), strict=True):
                    ids, start = ids + end, 0
                    total = len(ids) // 4
                    while start < total:
                        take = min(width - size, total - start)
                        held.append(ids[start * 4 : (start + take) * 4])
                        pieces.append({"doc_id": doc_id, "start": start, "length": take})
                        start, size = start + take, size + take
                        if size == width:
                            close()
                yield out()
        if size:
            close()
        yield out()

    return docs.select("doc_id", "text").mapInArrow(run, f"part int, idx long, n_tokens int, pieces {PIECE}, packed binary")


def opened(packed: str, width: int = SEQUENCE_TOKENS) -> Column:
    """The ids of compressed sequences."""

    @F.pandas_udf("binary")
    def ids(column: pd.Series) -> pd.Series:
        return column.map(lambda x: restored(x, width))

    return ids(packed)


def training_order(docs: DataFrame, tokenizer_path: str, width: int = SEQUENCE_TOKENS, shard_slots: int = SHARD_SLOTS, key: int = KEY, packed: bool = False) -> DataFrame:
    """One row per sequence in slot order: slot, shard, byte_offset, n_tokens, pieces, ids (or packed)."""
    rows = stored(sequences(docs, tokenizer_path, width))
    parts = rows.groupBy("part").agg(F.count("*").alias("n"))
    before = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    total = rows.count()

    @F.pandas_udf("long")
    def slot(number: pd.Series) -> pd.Series:
        return pd.Series(feistel(number.to_numpy(np.int64), total, key))

    placed = rows.join(F.broadcast(before) if parts.count() <= 100_000 else before, "part").withColumn("slot", slot(F.col("base") + F.col("idx")))
    shards = max(1, -(-total // shard_slots))
    ordered = placed.withColumn("shard", F.expr(f"slot div {shard_slots}")).repartitionByRange(shards, "shard").sortWithinPartitions("slot")
    return ordered.select("slot", "shard", (F.col("slot") % shard_slots * (2 * width)).alias("byte_offset"), "n_tokens", "pieces", "packed" if packed else opened("packed", width).alias("ids"))


def mounted(folder: str) -> str:
    """The path of a folder that executors open as files."""
    url = urlparse(folder)
    if url.scheme not in ("", "file"):
        raise ValueError(f"shards need a mounted folder, not {folder}")
    return url.path


def write_shards(ordered: DataFrame, folder: str, width: int = SEQUENCE_TOKENS, shard_slots: int = SHARD_SLOTS) -> DataFrame:
    """Writes shard-N.bin files of fixed stride under a folder that all executors mount; returns shard, slots, crc32.

    Each file is renamed into place when it is whole, so a lost task may run again.
    """
    path, name = mounted(folder), "packed" if "packed" in ordered.columns else "ids"

    def run(batches: Iterator) -> Iterator:
        os.makedirs(path, exist_ok=True)
        state: dict[int, list] = {}
        for shards, slots, found in columns(batches, "shard", "slot", name):
            for shard, slot, data in zip(shards, slots, found, strict=True):
                data = restored(data, width) if name == "packed" else data
                if shard not in state:
                    state[shard] = [open(f"{path}/.shard-{shard:06d}.{TaskContext.get().taskAttemptId()}", "wb"), 0, 0]
                f = state[shard]
                f[0].seek(slot % shard_slots * 2 * width)
                f[0].write(data)
                f[1], f[2] = f[1] + 1, zlib.crc32(data, f[2])
        for shard, (f, _, _) in state.items():
            f.close()
            os.replace(f.name, f"{path}/shard-{shard:06d}.bin")
        yield pa.RecordBatch.from_arrays([pa.array(list(state), pa.int64()), pa.array([s[1] for s in state.values()], pa.int64()), pa.array([s[2] for s in state.values()], pa.int64())], ["shard", "slots", "crc32"])

    return ordered.select("shard", "slot", name).mapInArrow(run, "shard long, slots long, crc32 long")


def read_slots(folder: str, first: int, count: int, width: int = SEQUENCE_TOKENS, shard_slots: int = SHARD_SLOTS) -> np.ndarray:
    """Ids of ``count`` slots from slot ``first`` on, read at their place."""
    out = []
    for slot in range(first, first + count):
        with open(f"{mounted(folder)}/shard-{slot // shard_slots:06d}.bin", "rb") as f:
            f.seek(slot % shard_slots * 2 * width)
            out.append(np.frombuffer(f.read(2 * width), "<u2"))
    return np.stack(out)


def read_back(ordered: DataFrame, folder: str, width: int = SEQUENCE_TOKENS, shard_slots: int = SHARD_SLOTS) -> DataFrame:
    """slot, shard, byte_offset, n_tokens, ids_crc32, pieces; the checksum is of the stride that the shard file holds at that place."""
    path, stride = mounted(folder), 2 * width

    def run(batches: Iterator) -> Iterator:
        f, opened = None, None
        for batch in batches:
            crc = []
            for shard, at in zip(batch.column("shard").to_pylist(), batch.column("byte_offset").to_pylist(), strict=True):
                if shard != opened:
                    if f:
                        f.close()
                    f, opened = open(f"{path}/shard-{shard:06d}.bin", "rb"), shard
                f.seek(at)
                data = f.read(stride)
                if len(data) < stride:
                    raise ValueError(f"shard {shard} ends inside the slot at byte {at}")
                crc.append(zlib.crc32(data))
            kept = [batch.column(c) for c in ("slot", "shard", "byte_offset", "n_tokens")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(crc, pa.int64()), batch.column("pieces")], ["slot", "shard", "byte_offset", "n_tokens", "ids_crc32", "pieces"])
        if f:
            f.close()

    rows = ordered.select("slot", "shard", "byte_offset", "n_tokens", "pieces")
    return rows.mapInArrow(run, f"slot long, shard long, byte_offset long, n_tokens int, ids_crc32 long, pieces {PIECE}")


def op6_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes the shards of all sequences; slot, shard, byte_offset, n_tokens, ids_crc32 (of the stride on disk), pieces of each.

    The files are those of a new folder shards-* in the checkpoint folder.
    """
    rows = training_order(documents(spark, sf_dir), default_path(), packed=True)
    folder = f"{checkpoints(spark)}/shards-{uuid.uuid4().hex}"
    write_shards(rows, folder).agg(F.sum("slots")).collect()
    return read_back(rows, folder)
