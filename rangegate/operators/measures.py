"""Accuracy and cost measures of filters over answers (qid, run_id, maybe, n_trie, n_bloom) and the truth."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def observed_fpr(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """n_empty, fpr: share of empty queries that some run's filter lets through; false_negatives must be 0.

    A query without any answer was not ruled out and counts as let through.
    """
    one = answers.groupBy("qid").agg(F.bool_or("maybe").alias("maybe"))
    both = truth.join(one, "qid", "left").withColumn("maybe", F.coalesce("maybe", F.lit(True)))
    empty = F.col("is_empty")
    return both.agg(F.sum(empty.cast("long")).alias("n_empty"), F.round(F.avg(F.when(empty, F.col("maybe").cast("double"))), 6).alias("fpr"), F.sum((~empty & ~F.col("maybe")).cast("long")).alias("false_negatives"))


def bits_per_key(filters: DataFrame) -> DataFrame:
    """Per run and over all runs (null run_id): keys, bits, bits per key."""
    return filters.rollup("run_id").agg(F.sum("n_keys").alias("n_keys"), F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n_keys"), 6).alias("bpk"))


def probe_counts(answers: DataFrame) -> DataFrame:
    return answers.agg(F.round(F.avg("n_bloom"), 6).alias("avg_bloom"), F.max("n_bloom").alias("max_bloom"), F.round(F.avg("n_trie"), 6).alias("avg_trie"))


def resolved_in_trie(profile: DataFrame, depth: int) -> DataFrame:
    """Share of empty queries that share fewer than ``depth`` bits with every key."""
    return profile.where("is_empty").agg(F.round(F.avg((F.col("near") < depth).cast("double")), 6).alias("resolved"))


def false_reads(asked: DataFrame, rows: DataFrame) -> DataFrame:
    """Surviving (run, query) pairs and how many of them hold no key; the keys of a run meet its queries by binary search."""

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        codes = np.sort(left.column("code").to_numpy())
        hit = np.searchsorted(codes, right.column("hi").to_numpy(), side="right") > np.searchsorted(codes, right.column("lo").to_numpy())
        return pa.table({"run_id": right.column("run_id"), "hit": pa.array(hit)})

    pairs = rows.select("run_id", "code").groupBy("run_id").cogroup(asked.select(*[F.col(c).alias(c) for c in ("run_id", "lo", "hi")]).groupBy("run_id")).applyInArrow(run, "run_id long, hit boolean")
    return pairs.agg(F.count("*").alias("reads"), F.sum((~F.col("hit")).cast("long")).alias("false_reads"), F.count_distinct("run_id").alias("runs"))


def io_costs(overlap: DataFrame, kept: DataFrame, sizes: DataFrame) -> DataFrame:
    """Pairs and bytes that overlap a query, and those left after the filters: read, avoided, and the distinct runs touched.

    Bytes count once a (run, query) pair, as a lookup at a time reads them; distinct runs stand for what a cache must hold.
    """
    asked = overlap.select("run_id", "qid").join(kept.select("run_id", "qid", F.lit(1).alias("read")), ["run_id", "qid"], "left").fillna(0, ["read"])
    both = asked.join(sizes, "run_id")
    out = both.agg(F.count("*").alias("overlaps"), F.sum("read").cast("long").alias("reads"), F.sum("bytes").alias("bytes_overlapping"), F.sum(F.col("read") * F.col("bytes")).alias("bytes_read"), F.count_distinct(F.when(F.col("read") == 1, F.col("run_id"))).alias("runs_touched"))
    return out.withColumn("bytes_avoided", F.col("bytes_overlapping") - F.col("bytes_read"))


def design_regret(expected: DataFrame, observed: DataFrame) -> DataFrame:
    """Observed rate of the design with the smallest expected rate, and the best observed one."""
    both = expected.join(observed, ["l1", "l2"])
    return both.agg(F.min_by("observed", "exp_fpr").alias("chosen"), F.min("observed").alias("best"))


def memory_split(filters: DataFrame) -> DataFrame:
    """run_id, trie_bits, bloom_bits, and their shares."""
    bloom = F.aggregate("m", F.lit(0).cast("long"), lambda a, x: a + x)
    rows = filters.select("run_id", "bits", bloom.alias("bloom_bits")).withColumn("trie_bits", F.col("bits") - F.col("bloom_bits"))
    return rows.select("run_id", "trie_bits", "bloom_bits", (F.col("trie_bits") / F.col("bits")).alias("trie_share"))


def footprint_spread(filters: DataFrame) -> DataFrame:
    """Least, mean and largest bits per key over the runs."""
    bpk = F.col("bits") / F.col("n_keys")
    return filters.agg(F.min(bpk).alias("least"), (F.sum("bits") / F.sum("n_keys")).alias("mean"), F.max(bpk).alias("largest"))


def timed(job: Callable[[], DataFrame]) -> float:
    """Seconds of a job whose rows are read and dropped."""
    began = time.perf_counter()
    job().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
