"""What the model needs to know of keys and queries: prefix counts, covers, proximity."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangegate.functions.keys import KeySpace, bit_length_numpy

BROADCAST_QUERIES = 2_000_000


def key_prefixes(keys: DataFrame, space: KeySpace, length: int) -> DataFrame:
    """Distinct prefixes of one length: run_id, prefix."""
    return keys.select("run_id", space.prefix("code", length).alias("prefix")).distinct()


def neighbour_lcp(keys: DataFrame, space: KeySpace) -> DataFrame:
    """run_id, code, lcp with the key before it in its run (null for the first)."""
    before = F.lag("code").over(Window.partitionBy("run_id").orderBy("code"))
    return keys.select("run_id", "code", space.lcp("code", before).alias("lcp"))


def _histogram(keys: DataFrame, bits: int) -> DataFrame:
    """run_id, lcp, c: how many keys share ``lcp`` bits with the key before them (-1: no key before).

    Keys are dealt by ranges of (run_id, code), so a run of any size is spread over tasks; what meets at the ends of two
    tasks is one row a task and run, stitched afterwards.
    """

    def run(batches: Iterator) -> Iterator:
        part, held, ends = TaskContext.get().partitionId(), {}, {}
        for batch in batches:
            run_ids, codes = batch.column("run_id").to_numpy(), batch.column("code").to_numpy()
            for r in np.unique(run_ids).tolist():
                own = codes[run_ids == r]
                if r in ends:
                    own = np.r_[ends[r][1], own]
                own = own[np.r_[True, own[1:] != own[:-1]]]
                common = np.maximum(bits - bit_length_numpy(own[1:] ^ own[:-1]), 0)  # codes beyond the space may share less than nothing
                held[r] = held.get(r, 0) + np.bincount(common, minlength=bits + 1)
                ends[r] = (ends[r][0] if r in ends else own[0], own[-1])
        rows = [(r, int(x), int(c[x]), None, None, None) for r, c in held.items() for x in np.flatnonzero(c)]
        rows += [(r, None, None, part, int(a), int(b)) for r, (a, b) in ends.items()]
        names = ("run_id", "lcp", "c", "part", "first", "last")
        columns = zip(*rows, strict=True) if rows else ((),) * 6
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in columns], list(names))

    dealt = keys.select("run_id", "code").repartitionByRange("run_id", "code").sortWithinPartitions("run_id", "code")
    rows = dealt.mapInArrow(run, "run_id long, lcp long, c long, part long, first long, last long")
    before = F.lag("last").over(Window.partitionBy("run_id").orderBy("first"))
    seams = rows.where("lcp is null").withColumn("before", before)
    seams = seams.select("run_id", F.when(F.col("before").isNull(), F.lit(-1)).otherwise(KeySpace(bits).lcp("first", "before")).cast("long").alias("lcp"), F.lit(1).cast("long").alias("c"))
    return rows.where("lcp is not null").select("run_id", "lcp", "c").unionByName(seams).groupBy("run_id", "lcp").agg(F.sum("c").alias("c"))


def prefix_counts(keys: DataFrame, space: KeySpace, method: str = "lcp") -> DataFrame:
    """run_id, l, n: distinct l-bit prefixes for l = 1 .. k.

    ``lcp`` sorts the keys once: a key starts a new prefix of every length over its common prefix with the key before it.
    ``distinct`` counts each length by itself; ``sketch`` estimates them.
    """
    lengths = F.explode(F.sequence(F.lit(1), F.lit(space.bits))).alias("l")
    if method == "lcp":
        rows = _histogram(keys, space.bits).where(F.col("lcp") < space.bits)
        new = rows.select("run_id", "c", F.explode(F.sequence(F.greatest(F.col("lcp").cast("int") + 1, F.lit(1)), F.lit(space.bits))).alias("l"))
        return new.groupBy("run_id", "l").agg(F.sum("c").alias("n"))
    spread = keys.select("run_id", "code", lengths).select("run_id", "l", space.prefix("code", F.col("l")).alias("p"))
    return spread.groupBy("run_id", "l").agg((F.count_distinct("p") if method == "distinct" else F.hll_sketch_estimate(F.hll_sketch_agg("p"))).cast("long").alias("n"))


def query_cover(queries: DataFrame, space: KeySpace) -> DataFrame:
    """qid, l, first, last, span for every length."""
    rows = queries.select("*", F.explode(F.sequence(F.lit(1), F.lit(space.bits))).alias("l"))
    return rows.select("qid", "l", space.prefix("lo", F.col("l")).alias("first"), space.prefix("hi", F.col("l")).alias("last")).withColumn("span", F.col("last") - F.col("first") + 1)


def neighbours(keys: DataFrame, queries: DataFrame, strategy: str = "broadcast") -> DataFrame:
    """run_id, qid, lo, hi, pred (greatest key below lo), succ (least key at or above lo).

    ``broadcast``: a bounded query sample meets every partition of keys by binary search; two values a query leave each
    partition. ``asof_join``: keys and bounds are dealt by ranges and sorted together, and what a task cannot see comes
    from one row a task. ``union_window``: keys and bounds are sorted together within runs.
    """
    if strategy == "asof_join":
        return _asof(keys, queries)
    runs = keys.select("run_id").distinct()
    if strategy == "broadcast":
        sample = queries.select("qid", "lo", "hi").toArrow() if queries.count() <= BROADCAST_QUERIES else None
        if sample is None:
            strategy = "union_window"
        else:
            shared = keys.sparkSession.sparkContext.broadcast((sample.column("qid").to_numpy(), sample.column("lo").to_numpy()))

            def run(batches: Iterator) -> Iterator:
                qid, lo = shared.value
                best: dict[int, list[np.ndarray]] = {}
                for batch in batches:
                    run_ids, codes = batch.column("run_id").to_numpy(), batch.column("code").to_numpy()
                    for r in np.unique(run_ids):
                        own = np.sort(codes[run_ids == r])
                        at = np.searchsorted(own, lo)
                        pred = np.where(at > 0, own[np.maximum(at - 1, 0)], -1)
                        succ = np.where(at < len(own), own[np.minimum(at, len(own) - 1)], np.iinfo(np.int64).max)
                        held = best.setdefault(int(r), [pred, succ])
                        held[0], held[1] = np.maximum(held[0], pred), np.minimum(held[1], succ)
                for r, (pred, succ) in best.items():
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(qid), r)), pa.array(qid), pa.array(pred), pa.array(succ)], ["run_id", "qid", "pred", "succ"])

            near = keys.select("run_id", "code").mapInArrow(run, "run_id long, qid long, pred long, succ long").groupBy("run_id", "qid").agg(F.max("pred").alias("pred"), F.min("succ").alias("succ"))
            top = F.lit((1 << 63) - 1)
            return queries.select("qid", "lo", "hi").join(near, "qid").select("run_id", "qid", "lo", "hi", F.when(F.col("pred") >= 0, F.col("pred")).alias("pred"), F.when(F.col("succ") < top, F.col("succ")).alias("succ"))
    marks = queries.crossJoin(F.broadcast(runs)).select("run_id", F.col("lo").alias("at"), F.lit(0).alias("kind"), "qid", "lo", "hi")
    rows = marks.unionByName(keys.select("run_id", F.col("code").alias("at"), F.lit(1).alias("kind")), allowMissingColumns=True)
    order = Window.partitionBy("run_id").orderBy("at", "kind")  # a bound comes before an equal key
    key = F.when(F.col("kind") == 1, F.col("at"))
    pred = F.last(key, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1))
    back = Window.partitionBy("run_id").orderBy(F.desc("at"), F.desc("kind"))  # a frame that only grows is walked once
    succ = F.last(key, ignorenulls=True).over(back.rowsBetween(Window.unboundedPreceding, -1))
    return rows.withColumns({"pred": pred, "succ": succ}).where("kind = 0").select("run_id", "qid", "lo", "hi", "pred", "succ")


def _asof(keys: DataFrame, queries: DataFrame) -> DataFrame:
    """run_id, qid, lo, hi, pred, succ for any number of queries and any size of runs."""

    def run(batches: Iterator) -> Iterator:
        part = TaskContext.get().partitionId()
        table = pa.Table.from_batches(list(batches)) if (batches := list(batches)) else None
        if table is None:
            return
        run_ids, at, is_key = (table.column(c).to_numpy() for c in ("run_id", "at", "is_key"))
        for r in np.unique(run_ids).tolist():
            own, asked = np.sort(at[(run_ids == r) & is_key]), np.flatnonzero((run_ids == r) & ~is_key)
            place = np.searchsorted(own, at[asked])
            below, above = place > 0, place < len(own)
            safe = own if len(own) else np.zeros(1, np.int64)
            pred = pa.array(safe[np.maximum(place - 1, 0)], pa.int64(), mask=~below)
            succ = pa.array(safe[np.minimum(place, len(safe) - 1)], pa.int64(), mask=~above)
            picked = table.take(pa.array(asked))
            n = len(asked)
            yield from pa.table({"run_id": pa.array([r] * n, pa.int64()), "part": pa.array([part] * n, pa.int64()), "qid": picked.column("qid"), "lo": picked.column("lo"), "hi": picked.column("hi"), "pred": pred, "succ": succ}).to_batches()
            ends = [int(own[0]), int(own[-1])] if len(own) else [None, None]
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (r, part, None, None, None, ends[1], ends[0])], ["run_id", "part", "qid", "lo", "hi", "pred", "succ"])

    marks = queries.crossJoin(F.broadcast(keys.select("run_id").distinct())).select("run_id", F.col("lo").alias("at"), F.lit(False).alias("is_key"), "qid", "lo", "hi")
    both = marks.unionByName(keys.select("run_id", F.col("code").alias("at"), F.lit(True).alias("is_key")), allowMissingColumns=True)
    dealt = both.repartitionByRange("run_id", "at").sortWithinPartitions("run_id", "at")
    rows = dealt.mapInArrow(run, "run_id long, part long, qid long, lo long, hi long, pred long, succ long")
    over = Window.partitionBy("run_id").orderBy("part")
    seams = rows.where("qid is null").select("run_id", "part", F.max("pred").over(over.rowsBetween(Window.unboundedPreceding, -1)).alias("below"), F.min("succ").over(over.rowsBetween(1, Window.unboundedFollowing)).alias("above"))
    found = rows.where("qid is not null").join(F.broadcast(seams), ["run_id", "part"])  # one row a task and run
    return found.select("run_id", "qid", "lo", "hi", F.coalesce("pred", "below").alias("pred"), F.coalesce("succ", "above").alias("succ"))


def profile_queries(keys: DataFrame, queries: DataFrame, space: KeySpace, strategy: str = "broadcast") -> DataFrame:
    """run_id, qid, lo, hi, pred, succ, lcp_l, lcp_r, near, is_empty; a null bound rejects its query.

    ``succ`` is the least key at or above lo, so the query is empty exactly when it lies beyond hi.
    """
    rows = neighbours(keys, queries.where("lo is not null and hi is not null"), strategy)
    left, right = F.coalesce(space.lcp("lo", "pred"), F.lit(0)), F.coalesce(space.lcp("hi", "succ"), F.lit(0))
    rows = rows.withColumns({"lcp_l": left, "lcp_r": right, "is_empty": F.coalesce(F.col("succ") > F.col("hi"), F.lit(True))})
    return rows.withColumn("near", F.greatest("lcp_l", "lcp_r"))


def nonempty_exact(keys: DataFrame, queries: DataFrame) -> DataFrame:
    """qid of the queries that hold a key."""
    return profile_truth(keys, queries).where("not is_empty").select("qid")


def profile_truth(keys: DataFrame, queries: DataFrame) -> DataFrame:
    rows = neighbours(keys, queries)
    return rows.groupBy("qid").agg(F.bool_and(F.coalesce(F.col("succ") > F.col("hi"), F.lit(True))).alias("is_empty"))
