"""Sample of executed empty queries: a first-in-first-out queue that every n-th one enters, in batch and streaming form."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangegate.sources.store import write_store


def offer(queue: DataFrame, executed: DataFrame, capacity: int = 20_000, every: int = 100) -> DataFrame:
    """seq, lo, hi after the empty queries ``executed(seq, lo, hi)`` ran; seed rows have numbers below zero.

    The live queue is the ``capacity`` entries with the largest numbers. Places in the order come from counts of ranges of
    numbers, so no task sorts more than one range and only a bounded top is sorted at one place.
    """
    ranges = executed.select("seq", "lo", "hi").repartitionByRange("seq").withColumn("part", F.spark_partition_id())
    own = Window.partitionBy("part").orderBy("seq")
    numbered = ranges.withColumn("rn", F.row_number().over(own))
    sizes = ranges.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))  # one row a task
    counted = numbered.join(F.broadcast(before), "part").where((F.col("before") + F.col("rn")) % every == 0).select("seq", "lo", "hi")
    return queue.select("seq", "lo", "hi").unionByName(counted).orderBy(F.desc("seq")).limit(capacity)


def stream_queue(executed: DataFrame, capacity: int = 20_000, every: int = 100) -> DataFrame:
    """The same queue over a stream of (store, seq, lo, hi): after each micro-batch one row a store with the whole live
    queue as arrays ``lo`` and ``hi``, so that filters can be tuned from it. The state is packed numbers of bounded size.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen, held = state.get if state.exists else (0, b"")
        queue = np.frombuffer(held, "<i8").reshape(-1, 3)
        for frame in frames:
            rows = frame.sort_values("seq")[["seq", "lo", "hi"]].to_numpy(np.int64)
            queue = np.concatenate([queue, rows[(seen + 1 + np.arange(len(rows))) % every == 0]])[-capacity:]
            seen += len(rows)
        state.update((seen, queue.astype("<i8").tobytes()))
        last = int(queue[-1, 0]) if len(queue) else -1
        yield pd.DataFrame({"store": [key[0]], "seen": [seen], "size": [len(queue)], "last_seq": [last], "lo": [queue[:, 1].tolist()], "hi": [queue[:, 2].tolist()]})

    return executed.groupBy("store").applyInPandasWithState(step, "store long, seen long, size long, last_seq long, lo array<long>, hi array<long>", "seen long, queue binary", "update", "NoTimeout")


def probe_stream(queries: DataFrame, set_bits: DataFrame, positions, space, length: int, most: int = 64) -> DataFrame:
    """A stream of queries (qid, lo, hi) against the set bits of a static filter: qid, x, n_set for every covering prefix.

    A prefix says yes when as many of its positions are set as it has; queries over ``most`` prefixes say yes unasked.
    """
    first, last = space.prefix("lo", length), space.prefix("hi", length)
    asked = queries.select("qid", F.explode(F.sequence(first, F.least(last, first + most))).alias("x"))
    return asked.select("qid", "x", F.explode(F.array_distinct(positions(F.col("x")))).alias("pos")).join(set_bits, "pos").groupBy("qid", "x").agg(F.count("*").alias("n_set"))


def distinct_keys(keys: DataFrame, delay: str = "1 hour") -> DataFrame:
    """A stream of inserts (code, at) without the keys seen before within the watermark."""
    timed = keys.withWatermark("at", delay)
    return timed.dropDuplicatesWithinWatermark(["code"]) if keys.isStreaming else timed.dropDuplicates(["code"])


def event_windows(events: DataFrame, length: str, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Counts of events by tumbling, sliding or (``gap``) session windows of their time; works on batches and streams."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("at", length) if events.isStreaming else timed
    window = F.session_window("at", gap) if gap else F.window("at", length, slide) if slide else F.window("at", length)
    return timed.groupBy(window.alias("window"), "event_type").agg(F.count("*").alias("n"))


def insert_stream(inserts: DataFrame, path: str, cut: Callable[[DataFrame], DataFrame]):
    """Writer of a stream of inserts into a store: each micro-batch becomes runs of its own, cut by ``cut``."""

    def flush(batch: DataFrame, number: int) -> None:
        write_store(cut(batch), path, mode="append")

    return inserts.writeStream.foreachBatch(flush)
