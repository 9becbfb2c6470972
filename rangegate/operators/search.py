"""Choice of a design: trie memory, evidence of the query sample, expected rates of all designs, the best one."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangegate.functions.amq import bloom_fpr, one_minus_pow, probe_bin
from rangegate.functions.keys import KeySpace
from rangegate.operators.model import fpr_dual, fpr_single, probes

RANK_OVERHEAD = 1 / 16


def trie_bits(counts: DataFrame, bits: int, rank_overhead: float = RANK_OVERHEAD) -> DataFrame:
    """run_id, l, dense_levels, bits: memory of a uniform trie of each depth, from prefix counts only.

    Byte levels at the top are bitmaps, those below are label lists; the cut that needs least memory is taken.
    """
    base = counts.select("run_id", "l", "n").unionByName(counts.select("run_id", F.lit(0).alias("l"), F.lit(1).cast("long").alias("n")).distinct())
    depths = counts.select("run_id", "l").withColumn("level", F.explode(F.sequence(F.lit(0), F.floor((F.col("l") - 1) / 8).cast("int"))))
    levels = depths.withColumns({"s": F.col("level") * 8, "e": F.least(F.col("level") * 8 + 8, F.col("l"))})
    at = lambda c, n: base.select("run_id", F.col("l").alias(c), F.col("n").alias(n))
    rows = levels.join(at("s", "ns"), ["run_id", "s"]).join(at("e", "ne"), ["run_id", "e"])
    w = F.col("e") - F.col("s")
    rows = rows.withColumns({"dense": F.col("ns") * (2 * F.call_function("shiftleft", F.lit(1).cast("long"), w) + 1), "sparse": F.col("ne") * (w + 2)})
    order = Window.partitionBy("run_id", "l").orderBy("level")
    rows = rows.withColumn("gain", F.sum(F.col("dense") - F.col("sparse")).over(order))
    best = rows.groupBy("run_id", "l").agg(F.sum("sparse").alias("sparse"), F.min(F.struct("gain", "level")).alias("b"))
    cut = F.col("b.gain") < 0
    return best.select("run_id", "l", F.when(cut, F.col("b.level") + 1).otherwise(0).cast("int").alias("dense_levels"), F.ceil((F.col("sparse") + F.when(cut, F.col("b.gain")).otherwise(0)) * (1 + rank_overhead)).cast("long").alias("bits"))


def feasible_depths(tries: DataFrame, memory: DataFrame) -> DataFrame:
    """run_id, l1, trie of all depths within ``memory(run_id, m)``, with depth 0 for no trie."""
    fit = tries.join(memory, "run_id").where("bits <= m").select("run_id", F.col("l").alias("l1"), F.col("bits").alias("trie"), "m")
    return fit.unionByName(memory.select("run_id", F.lit(0).alias("l1"), F.lit(0).cast("long").alias("trie"), "m"))


def design_evidence(profile: DataFrame, depths: DataFrame, space: KeySpace, binning: str = "exp2", grid: list[int] | None = None) -> DataFrame:
    """run_id, l1, l2, bin, n_queries, avg_probes; bin -1 counts certain false positives, l2 = 0 trie-only designs.

    Rows of a design are combined in each task, so at most one row a bin is shuffled whatever the sample.
    """
    sample = profile.where("is_empty").select("run_id", "qid", "lo", "hi", "lcp_l", "lcp_r", "near")
    lengths = F.array(*[F.lit(x) for x in grid]) if grid else F.sequence(F.lit(1), F.lit(space.bits))
    rows = sample.join(F.broadcast(depths.select("run_id", "l1")), "run_id").withColumn("l2", F.explode(F.array_union(F.array(F.lit(0)), lengths)))
    rows = rows.where("l2 > l1 or (l2 = 0 and l1 > 0)")
    certain = F.when(F.col("l2") == 0, F.col("near") >= F.col("l1")).otherwise(F.col("near") >= F.col("l2"))
    n = F.when(F.col("l2") == 0, 0).otherwise(probes(space, F.col("l1"), F.greatest(F.col("l2"), F.col("l1"))))
    rows = rows.select("run_id", "l1", "l2", certain.alias("certain"), n.alias("n"))
    key = F.when(F.col("certain"), F.lit(-1).cast("long")).otherwise(probe_bin(F.col("n")).cast("long") if binning == "exp2" else F.col("n"))
    return rows.groupBy("run_id", "l1", "l2", key.alias("bin")).agg(F.count("*").alias("n_queries"), F.avg(F.when(F.col("certain"), 0.0).otherwise(F.col("n").cast("double"))).alias("avg_probes"))


def design_space_fpr(evidence: DataFrame, counts: DataFrame, depths: DataFrame, form: str = "load_aware", mode: str = "exact") -> DataFrame:
    """run_id, l1, l2, bloom (bits), p, exp_fpr of every design that leaves memory for its Bloom part."""
    sized = depths.join(counts.select("run_id", F.col("l").alias("l2"), "n"), "run_id").where("l2 > l1 and m - trie >= 1").select("run_id", "l1", "l2", (F.col("m") - F.col("trie")).alias("bloom"), bloom_fpr(F.col("m") - F.col("trie"), F.col("n"), form).alias("p"))
    alone = depths.where("l1 > 0").select("run_id", "l1", F.lit(0).alias("l2"), F.lit(0).cast("long").alias("bloom"), F.lit(0.0).alias("p"))
    rows = evidence.join(sized.unionByName(alone), ["run_id", "l1", "l2"])
    some = one_minus_pow(F.col("p"), F.col("avg_probes")) if mode == "exact" else F.least(F.lit(1.0), F.col("p") * F.col("avg_probes"))
    cost = F.when(F.col("bin") == -1, 1.0).otherwise(some) * F.col("n_queries")
    return rows.groupBy("run_id", "l1", "l2").agg(F.first("bloom").alias("bloom"), F.first("p").alias("p"), F.round(F.sum(cost) / F.sum("n_queries"), 9).alias("exp_fpr"))


def choose_design(rates: DataFrame, tie: str = "last") -> DataFrame:
    """Per run the design of the smallest rate; of equal ones the later or the earlier in (l1, l2)."""
    sign = -1 if tie == "last" else 1
    best = F.min_by(F.struct("l1", "l2", "bloom", "p", "exp_fpr"), F.struct("exp_fpr", F.col("l1") * sign, F.col("l2") * sign)).alias("d")
    return rates.groupBy("run_id").agg(best).select("run_id", "d.l1", "d.l2", "d.bloom", "d.p", "d.exp_fpr")


def memory_of(counts: DataFrame, bits: int, bpk: float) -> DataFrame:
    """run_id, m: the budget of a run at ``bpk`` bits a key."""
    return counts.where(F.col("l") == bits).select("run_id", F.floor(F.col("n") * bpk).cast("long").alias("m"))


def tune(profile: DataFrame, counts: DataFrame, space: KeySpace, bpk: float = 10, kind: str = "hybrid", binning: str = "exp2", form: str = "load_aware", mode: str = "exact", grid: list[int] | None = None) -> DataFrame:
    """Rates of all designs of a kind: ``single`` (no trie), ``hybrid`` or ``trie`` (no Bloom part)."""
    memory = memory_of(counts, space.bits, bpk)
    depths = feasible_depths(trie_bits(counts, space.bits), memory)
    if kind == "single":
        depths = depths.where("l1 = 0")
    rates = design_space_fpr(design_evidence(profile, depths, space, binning, grid), counts, depths, form, mode)
    return rates.where("l2 = 0") if kind == "trie" else rates


def tune_dual(profile: DataFrame, counts: DataFrame, space: KeySpace, bpk: float = 10, splits: tuple = (0.4, 0.5, 0.6), grid: list[int] | None = None, form: str = "product") -> DataFrame:
    """run_id, l1, l2, split, exp_fpr: two Bloom filters with shares of the memory.

    Without a grid the designs of one filter that has the whole memory are among them, with l1 and split 0.
    """
    memory = memory_of(counts, space.bits, bpk)
    lengths = grid or list(range(1, space.bits + 1))
    own = counts.join(memory, "run_id").where(F.col("l").isin(lengths))
    share = F.explode(F.array(*[F.lit(float(s)) for s in splits])).alias("split")
    first = own.select("run_id", F.col("l").alias("l1"), F.col("n").alias("n1"), "m", share)
    second = own.select("run_id", F.col("l").alias("l2"), F.col("n").alias("n2"))
    designs = first.join(second, "run_id").where("l1 < l2").select("run_id", "l1", "l2", "split", bloom_fpr(F.floor(F.col("m") * F.col("split")), F.col("n1")).alias("p1"), bloom_fpr(F.col("m") - F.floor(F.col("m") * F.col("split")), F.col("n2")).alias("p2"))
    if grid is None:
        designs = designs.unionByName(own.select("run_id", F.lit(0).alias("l1"), F.col("l").alias("l2"), F.lit(0.0).alias("split"), F.lit(1.0).alias("p1"), bloom_fpr(F.col("m"), F.col("n")).alias("p2")))
    rows = profile.where("is_empty").join(F.broadcast(designs), "run_id")
    two = fpr_dual(space, F.col("l1"), F.col("l2"), F.col("p1"), F.col("p2"), form)
    rate = F.when(F.col("l1") == 0, fpr_single(F.col("near"), space.span("lo", "hi", F.col("l2")), F.col("l2"), F.col("p2"))).otherwise(two)
    return rows.groupBy("run_id", "l1", "l2", "split").agg(F.round(F.avg(rate), 9).alias("exp_fpr"))
