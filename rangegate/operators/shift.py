"""Workload shift: queries of a new kind take over batch by batch while keys are inserted and runs merged.

Every filter is tuned on the queue of past empty queries as it is when its run is made. Beside it stand a frozen filter,
whose design is the first one for all time, the hierarchical filter and the filter of unique prefixes.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.functions.hashes import P, mix
from rangegate.operators import construct, filters, workload
from rangegate.operators.workload import KeySet

KINDS = ("adaptive", "frozen", "hierarchical", "unique_prefix")
BATCHES, MERGE_EVERY, RUN_KEYS = 12, 3, 20_000
REPORT = "batch int, filter string, n_empty long, fpr double, false_negatives long, rebuilt long, runs_read long, seconds double"


def mixed_batch(old: DataFrame, new: DataFrame, batch: int, batches: int, kind: str = "gradual") -> DataFrame:
    """Queries of one batch: a query id takes the new kind when its hash lies below the batch's ratio."""
    ratio = batch / max(1, batches - 1) if kind == "gradual" else float(2 * batch >= batches)
    late = mix(60 + batch, F.col("qid")) < F.lit(int(ratio * P))
    return new.where(late).unionByName(old.where(~late))


def four_filters(codes: np.ndarray, sample: tuple, first: tuple, bits: int, bpk: float) -> list[tuple[str, dict]]:
    """Filter rows of a run: tuned on the live sample, tuned on the first one, and the two baselines at the same budget."""
    out, m = [], int(len(codes) * bpk)
    for name, given in (("adaptive", sample), ("frozen", first)):
        _, best, told = construct.tune_run(codes, *given, bits, bpk)
        out.append((name, construct.built(codes, bits, "hybrid", best, told)))
    lengths, shares = filters.dyadic_levels(sample[1] - sample[0] + 1, bits, m)
    blooms = [filters.Bloom.of(filters._prefix(codes, bits, x), int(m * s)) for x, s in zip(lengths, shares, strict=True)]
    out.append(("hierarchical", {"kind": "dyadic", "lengths": lengths, "depth": 0, "m": [b.m for b in blooms], "h": [b.h for b in blooms], "words": [b.packed() for b in blooms], "trie": b"", "aux": b"", "n_keys": len(codes), "bits": sum(b.m for b in blooms)}))
    best = filters.best_suffix(codes, bits, m, *sample)
    if best:
        regions, marks, size = filters.unique_blob(codes, bits, *best[:2])
        out.append(("unique_prefix", {"kind": "unique_prefix", "lengths": [], "depth": 0, "m": [], "h": [best[0], best[1]], "words": [], "trie": bytes(regions), "aux": marks, "n_keys": len(codes), "bits": size}))
    return out


def _built(runs: DataFrame, sample: tuple, first: tuple, bits: int, bpk: float) -> DataFrame:
    shared = runs.sparkSession.sparkContext.broadcast((sample, first))  # two queues of bounded size

    def run(key, table):
        rows = [{"run_id": key[0].as_py(), "name": name} | f for name, f in four_filters(np.unique(table.column("code").to_numpy()), *shared.value, bits, bpk)]
        return pa.Table.from_pylist(rows, pa.schema([("run_id", pa.int64()), ("name", pa.string()), *filters.FILTER_ARROW[1:]]))

    return runs.select("run_id", "code").groupBy("run_id").applyInArrow(run, "run_id long, name string, " + filters.FILTER.split(", ", 1)[1])


def _asked(built: DataFrame, runs: DataFrame, queries: DataFrame, bits: int) -> DataFrame:
    """name, qid, maybe, read (some run was let through), held, of all runs of a batch; the queries of a batch are broadcast."""
    rows = queries.select("qid", "lo", "hi").toArrow()
    shared = runs.sparkSession.sparkContext.broadcast(tuple(rows.column(c).to_numpy() for c in ("qid", "lo", "hi")))

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        qid, lo, hi = shared.value
        codes = np.unique(left.column("code").to_numpy())
        near = np.flatnonzero((hi >= codes[0]) & (lo <= codes[-1])) if len(codes) else np.zeros(0, np.int64)
        qid, lo, hi = qid[near], lo[near], hi[near]
        held = np.searchsorted(codes, hi, side="right") > np.searchsorted(codes, lo)
        out = [pa.table({"name": pa.array([f["name"]] * len(qid)), "qid": pa.array(qid), "maybe": pa.array(filters.answer(f, bits, lo, hi)[0]), "held": pa.array(held)}) for f in right.to_pylist() if len(qid)]
        return pa.concat_tables(out) if out else pa.table({"name": pa.array([], pa.string()), "qid": pa.array([], pa.int64()), "maybe": pa.array([], pa.bool_()), "held": pa.array([], pa.bool_())})

    return runs.select("run_id", "code").groupBy("run_id").cogroup(built.select(*[F.col(c).alias(c) for c in built.columns]).groupBy("run_id")).applyInArrow(run, "name string, qid long, maybe boolean, held boolean")


def shift_report(spark: SparkSession, keys: DataFrame, ks: KeySet, old: DataFrame, new: DataFrame, batches: int = BATCHES, bpk: float = 10, kind: str = "gradual", capacity: int = 2_000, every: int = 2, merge_every: int = MERGE_EVERY) -> DataFrame:
    """One row a batch and filter: rate on empty queries, false negatives, filters made, runs let through, seconds.

    A third of the keys is there at the start, the others come in equal parts; each batch's inserts make new runs with
    filters of their own, and every ``merge_every`` batches all runs are merged and their filters made again. The loop runs over
    batches, which are few; each step is two jobs over tables.
    """
    code = F.col("code")
    born = F.when(mix(70, code) % 3 == 0, 0).otherwise((mix(71, code) % batches).cast("int"))
    dealt = keys.select("code", born.alias("born")).persist()
    wide = 1 + dealt.count() // RUN_KEYS
    sample = first = None
    live: list[tuple[DataFrame, DataFrame]] = []
    report = []
    for batch in range(batches):
        began = time.perf_counter()
        queries = mixed_batch(old.where(f"qid % {batches} = {batch}"), new.where(f"qid % {batches} = {batch}"), batch, batches, kind).persist()
        if sample is None:  # the queue is seeded with queries of the first kind
            rows = old.where("qid % 3 = 0").orderBy("qid").limit(capacity).toArrow()
            sample = first = (rows.column("lo").to_numpy(), rows.column("hi").to_numpy())
        merged = batch and batch % merge_every == 0
        stays = dealt.where(f"born <= {batch}" if merged or not batch else f"born = {batch}")
        runs = stays.withColumn("run_id", F.lit(batch << 20) + (F.shiftrightunsigned("code", max(0, ks.bits - 20)) * wide / (1 << 20)).cast("long")).persist()
        built = _built(runs, sample, first, ks.bits, bpk).persist()
        live = [(runs, built)] if merged else [*live, (runs, built)]
        rebuilt = built.select("run_id").distinct().count()
        answers = None
        for r, b in live:
            part = _asked(b, r, queries, ks.bits)
            answers = part if answers is None else answers.unionByName(part)
        names = spark.createDataFrame([(x,) for x in KINDS], "name string")
        one = answers.groupBy("name", "qid").agg(F.bool_or("maybe").alias("maybe"), F.bool_or("held").alias("held"), F.sum(F.col("maybe").cast("long")).alias("read"), F.sum((F.col("held") & ~F.col("maybe")).cast("long")).alias("lost")).persist()
        told = queries.select("qid").crossJoin(F.broadcast(names)).join(one, ["name", "qid"], "left").fillna(False, ["maybe", "held"]).fillna(0, ["read", "lost"])
        rows = told.groupBy("name").agg(F.sum((~F.col("held")).cast("long")), F.round(F.avg(F.when(~F.col("held"), F.col("maybe").cast("double"))), 6), F.sum("lost"), F.sum("read")).collect()
        empty = queries.join(one.where("held").select("qid").distinct(), "qid", "left_anti").orderBy("qid").select("lo", "hi").toArrow()
        lo, hi = (np.r_[x, empty.column(c).to_numpy()[every - 1 :: every]][-capacity:] for x, c in zip(sample, ("lo", "hi"), strict=True))
        sample = (lo, hi)
        spent = time.perf_counter() - began
        report += [(batch, r[0], r[1], r[2], r[3], rebuilt, r[4], spent) for r in rows]
    return spark.createDataFrame(report, REPORT)


def setup(spark: SparkSession, sf_dir: str, name: str, n: int = 6000) -> tuple[DataFrame, KeySet, DataFrame, DataFrame]:
    """Keys, their set, and uniform and correlated queries."""
    ks = workload.SETS[name]
    keys = workload.keys(spark, sf_dir, name)
    return keys, ks, workload.uniform_queries(spark, ks, n), workload.correlated_queries(keys, ks, n)
