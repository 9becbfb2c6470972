"""Worked examples, invariants of the model and filters, and queries against their DuckDB texts."""

import math
import os
import tracemalloc

import duckdb
import numpy as np
import pyarrow.compute as pc
import pytest
from pyspark.sql import functions as F

from rangegate import experiments  # noqa: F401  (registers its queries)
from rangegate import queries as engine
from rangegate.functions import amq, hashes, keys
from rangegate.functions.hashes import mix, mix_numpy
from rangegate.functions.keys import KeySpace
from rangegate.operators import compare, construct, filters, measures, model, profile, search, strings, trie, workload
from rangegate.sources import store

SF = "/root/testdata/sf0.001"
K16 = KeySpace(16)
NEW = ["acc_single_width", "best_dual_ts", "best_hybrid_unbinned", "design_matrix_ts", "points_present", "lsm_seek_val_real", "read_formats", "range_store_scan", "star_after_pruning", "compaction_rebuild", "store_levels", "zorder_boxes", "dyadic_cover_ts", "dyadic_table_function", "dyadic_recursive", "sql_functions", "bloom_aggregate", "word_array_probe", "stream_sample_queue", "stream_probe", "events_session", "u64_edges", "enc_value_double", "false_negatives_hybrid"]
K12 = KeySpace(12)


def frame(spark, rows, names):
    return spark.createDataFrame(rows, names)


def small_profile(spark, lo, hi):
    kk = frame(spark, [(0, 0x100), (0, 0x900)], "run_id long, code long")
    return kk, profile.profile_queries(kk, frame(spark, [(1, lo, hi)], "qid long, lo long, hi long"), K12)


def test_hash_agrees_with_numpy(spark):
    total = spark.range(10_000).select(F.sum(mix(5, F.col("id"))).alias("s")).first().s
    assert total == 10699491854092 == int(mix_numpy(5, np.arange(10_000)).sum())


def test_sample_bound():
    assert [round(amq.sample_bound(x, 1.0), 6) for x in (1, 2)] == [0.042412, 0.001318]
    assert amq.sample_bound(amq.required_sample(0.01, 0.05), 0.01) <= 0.05


def test_bloom_rates():
    assert round(amq.bloom_fpr(10, 1), 5) == 0.00819 and round(amq.bloom_fpr(12, 1, "half_full"), 5) == 0.00195
    assert amq.bloom_fpr(0, 5) == 1.0 and amq.num_hashes(1000, 1) == 32


def test_dual_and_hybrid_worked_example(spark):
    _, p = small_profile(spark, 0x141, 0x8C3)
    one = lambda x: F.lit(x)
    row = p.select(model.fpr_dual(K12, one(4), one(8), one(0.1), one(0.05)).alias("dual"), model.fpr_hybrid(K12, one(4), one(8), one(0.05)).alias("hybrid"), model.fpr_dual(K12, one(4), one(8), one(0.1), one(0.05), "printed").alias("printed")).first()
    assert round(row.dual, 6) == 0.636183 and round(row.hybrid, 6) == 0.459640 and row.hybrid <= row.dual and 0 <= row.printed <= 1


def test_single_region_counts_once(spark):
    _, p = small_profile(spark, 0x141, 0x1C3)
    row = p.select(model.probes(K12, F.lit(4), F.lit(8)).alias("n"), model.fpr_hybrid(K12, F.lit(4), F.lit(8), F.lit(0.05)).alias("f"), model.fpr_dual(K12, F.lit(4), F.lit(8), F.lit(0.1), F.lit(0.05)).alias("d")).first()
    assert row.n == 9 and round(row.f, 5) == round(row.d, 5) == 0.36975


def test_closed_form_is_the_binomial_sum():
    for n in (0, 1, 7):
        assert math.isclose(model.interior_sum(n, 0.2, 0.1, 2), (1 - 0.2 + 0.2 * 0.9**4) ** n)


def test_three_probes_of_24_bits(spark):
    space = KeySpace(24)
    kk = frame(spark, [(0, 0x020011), (0, 0x450000)], "run_id long, code long")
    design = frame(spark, [(0, "hybrid", [20], 16, [4096], [0, 0], 0)], "run_id long, kind string, lengths array<int>, depth int, m array<long>, aux array<int>, trie_bits long")
    qs = frame(spark, [(0, 1, 0x00F200, 0x010000), (0, 2, 0x020073, 0x02009C)], "run_id long, qid long, lo long, hi long")
    rows = {r.qid: r for r in filters.probe(filters.build(kk, space.bits, design), qs, space.bits).collect()}
    assert (rows[1].maybe, rows[1].n_bloom) == (False, 0) and rows[2].n_bloom == 3


def test_prefix_lcp_and_bounds(spark):
    space = KeySpace(62)
    row = spark.range(1).select(space.lcp(F.lit(5), F.lit(5)).alias("same"), space.lcp(F.lit(0), F.lit(1 << 61)).alias("none"), space.prefix(F.lit(5), 0).alias("p0"), space.clip_add(F.lit((1 << 62) - 3), F.lit(10)).alias("top"), keys.unsigned_less(F.lit(-1), F.lit(1)).alias("u"), keys.zorder(F.lit(1), F.lit(0), 2).alias("z")).first()
    assert (row.same, row.none, row.p0, row.top, row.u, row.z) == (62, 0, 0, (1 << 62) - 1, False, 2)


@pytest.mark.parametrize("kind", ["levels", "hybrid", "trie", "unique"])
def test_no_false_negatives(spark, kind):
    rng = np.random.default_rng(3)
    codes = np.unique(rng.integers(0, 1 << 20, 300))
    lo = np.r_[codes[:100], rng.integers(0, 1 << 20, 200)]
    hi = np.minimum(lo + rng.integers(0, 3000, len(lo)), (1 << 20) - 1)
    kk = frame(spark, [(0, int(c)) for c in codes], "run_id long, code long")
    qs = frame(spark, [(0, i, int(a), int(b)) for i, (a, b) in enumerate(zip(lo, hi, strict=True))], "run_id long, qid long, lo long, hi long")
    design = {"levels": ("levels", [10, 16], 0, [900, 1800]), "hybrid": ("hybrid", [15], 9, [2500]), "trie": ("hybrid", [], 12, []), "unique": ("unique_prefix", [], 0, [])}[kind]
    designs = frame(spark, [(0, *design, [2, 3], 0)], "run_id long, kind string, lengths array<int>, depth int, m array<long>, aux array<int>, trie_bits long")
    answers = {r.qid: r.maybe for r in filters.probe(filters.build(kk, 20, designs), qs, 20).collect()}
    truth = [bool(((codes >= a) & (codes <= b)).any()) for a, b in zip(lo, hi, strict=True)]
    assert len(answers) == len(truth) and all(answers[i] for i, t in enumerate(truth) if t)
    assert sum(answers[i] for i, t in enumerate(truth) if not t) < truth.count(False)


def test_proximity_decides_emptiness_of_prefixes(spark):
    ks = workload.SETS["ts"]
    kk = workload.keys(spark, SF, "ts")
    p = profile.profile_queries(kk, workload.split_queries(spark, kk, ks, 200), ks.space).where("is_empty").collect()
    codes = np.sort(np.array([r.code for r in kk.collect()]))
    for length in (12, 20, 33):
        prefixes = np.unique(codes >> (42 - length))
        for r in p:
            a, b = r.lo >> (42 - length), r.hi >> (42 - length)
            assert (np.searchsorted(prefixes, b, side="right") > np.searchsorted(prefixes, a)) == (r.near >= length)


def test_dual_search_covers_all_lengths_and_one_filter(spark):
    rows = {(r.l1, r.l2, r.split): r.exp_fpr for r in engine.QUERIES["design_space_dual_ts"](spark, SF).collect()}
    k = workload.SETS["ts"].bits
    assert set(rows) == {(a, b, s) for b in range(1, k + 1) for a in range(1, b) for s in (0.4, 0.5, 0.6)} | {(0, b, 0.0) for b in range(1, k + 1)}
    assert engine.QUERIES["best_dual_ts"](spark, SF).first().exp_fpr == min(rows.values())


def test_search_prefers_hybrid_on_split(spark):
    ks = workload.SETS["ts"]
    kk = workload.keys(spark, SF, "ts").persist()
    p = profile.profile_queries(kk, workload.split_queries(spark, kk, ks, 400), ks.space).persist()
    counts = profile.prefix_counts(kk, ks.space).persist()
    rates = search.tune(p, counts, ks.space).persist()
    best = {k: search.choose_design(r).first().exp_fpr for k, r in (("hybrid", rates), ("single", rates.where("l1 = 0")), ("trie", rates.where("l2 = 0")))}
    assert best["hybrid"] <= best["single"] and best["hybrid"] <= best["trie"]
    exact = search.choose_design(search.tune(p, counts, ks.space, binning="none")).first().exp_fpr
    assert abs(exact - best["hybrid"]) < 0.02
    n = [r.n for r in counts.orderBy("l").collect()]
    assert n == sorted(n) and n[-1] == kk.count() and all(x <= min(1 << (i + 1), n[-1]) for i, x in enumerate(n))


@pytest.mark.parametrize("name", ["n_l_ts", "profile_ts_split", "trie_bits_ts_split", "evidence_hybrid", "best_hybrid_ts_split", "probe_hybrid_ts_uniform", "bloom_words_ts", "closed_seek", "sensor_match", "sample_queue", *NEW])
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    for t in os.listdir(SF):
        con.sql(f"create view {t.split('.')[0]} as select * from '{SF}/{t}'")
    got = engine.QUERIES[name](spark, SF)
    want = con.sql(engine.ORACLES[name])
    order = [want.columns.index(c) for c in got.columns]
    assert sorted(map(tuple, got.collect()), key=str) == sorted((tuple(r[i] for i in order) for r in want.fetchall()), key=str)


@pytest.mark.parametrize("depth", [5, 8, 13, 20])
def test_trie_round_trip_and_estimate(depth):
    prefixes = np.unique(np.random.default_rng(depth).integers(0, 1 << depth, 300))
    n = {l: len(np.unique(prefixes >> (depth - l))) if l else 1 for l in range(depth + 1)}
    for dense in range(-(-depth // 8) + 1):
        assert (trie.decode(trie.encode(prefixes, depth, dense)) == prefixes).all()
        cost = sum(n[s] * (2 * 2 ** (min(s + 8, depth) - s) + 1) if s // 8 < dense else n[min(s + 8, depth)] * (min(s + 8, depth) - s + 2) for s in range(0, depth, 8))
        assert trie.exact_bits(prefixes, depth, dense) <= math.ceil(cost * 17 / 16)


def test_filters_follow_a_shift(spark):
    rows = engine.QUERIES["shift_step"](spark, SF).collect()
    last = {r.filter: r.fpr for r in rows if r.batch == 7}
    assert last["adaptive"] <= last["frozen"] and last["adaptive"] <= last["hierarchical"] and all(r.false_negatives == 0 for r in rows)
    assert {r.filter for r in rows} >= {"adaptive", "frozen", "hierarchical"} and all(r.rebuilt > 0 for r in rows)


def test_stream_queue_keeps_every_nth(spark, tmp_path):
    from rangegate.streaming import queue

    spark.range(95).selectExpr("1L as store", "id as seq", "id * 2 as lo", "id * 2 + 1 as hi").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("store long, seq long, lo long, hi long").parquet(str(tmp_path / "in"))
    query = queue.stream_queue(stream, capacity=5, every=95 // 9).writeStream.format("memory").queryName("queue_out").outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    row = spark.table("queue_out").first()
    assert (row.seen, row.size, row.last_seq) == (95, 5, 89) and row.lo == [2 * x for x in (49, 59, 69, 79, 89)] and row.hi == [x + 1 for x in row.lo]


def one_run(spark, codes, run_id=0):
    return frame(spark, [(run_id, int(c)) for c in codes], "run_id long, code long")


def test_construction_agrees_with_the_dataframe_search(spark):
    ks = workload.SETS["ts"]
    kk = workload.keys(spark, SF, "ts").persist()
    qs = workload.split_queries(spark, kk, ks, 300).persist()
    p, counts = profile.profile_queries(kk, qs, ks.space).persist(), profile.prefix_counts(kk, ks.space).persist()
    want = {(r.l1, r.l2): r.exp_fpr for r in search.tune(p, counts, ks.space).collect()}
    got = {(r.l1, r.l2): r.exp_fpr for r in construct.all_rates(kk, qs, ks.bits, 10).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 2e-9 for k in want)
    duals = {(r.l1, r.l2, r.split): r.exp_fpr for r in search.tune_dual(p, counts, ks.space, grid=[12, 20, 31]).collect()}
    rates = {(r.l1, r.l2, r.split): r.exp_fpr for r in construct.all_rates(kk, qs, ks.bits, 10, "dual").collect()}
    assert all(abs(rates[k] - v) < 2e-9 for k, v in duals.items())


def test_search_in_parts_is_the_serial_search(spark):
    ks = workload.SETS["ts"]
    kk = workload.keys(spark, SF, "ts").persist()
    qs = workload.split_queries(spark, kk, ks, 100).persist()
    codes, (lo, hi) = compare.one_run(kk), compare.bounds(qs)
    want = {(r[0], r[1]): round(r[5], 9) for r in construct.tune_run(codes, lo, hi, ks.bits, 10)[0]}
    assert {(r.l1, r.l2): r.exp_fpr for r in compare.design_map(spark, kk, qs, ks.bits, 10).collect()} == want


@pytest.mark.parametrize("method", ["lcp", "distinct"])
def test_prefix_counts_of_many_runs(spark, method):
    rng = np.random.default_rng(1)
    rows = [(int(r), int(c)) for r in range(5) for c in rng.integers(0, 1 << 12, 200)]
    got = {(r.run_id, r.l): r.n for r in profile.prefix_counts(frame(spark, rows, "run_id long, code long").repartition(7), K12, method).collect()}
    assert got == {(r, l): len({c >> (12 - l) for q, c in rows if q == r}) for r in range(5) for l in range(1, 13)}


@pytest.mark.parametrize("strategy", ["broadcast", "asof_join", "union_window"])
def test_neighbours(spark, strategy):
    rng = np.random.default_rng(2)
    runs = {r: np.unique(rng.integers(0, 1 << 12, n)) for r, n in ((0, 40), (3, 1), (7, 300))}
    kk = frame(spark, [(r, int(c)) for r, cs in runs.items() for c in cs], "run_id long, code long").repartition(5)
    lo = [0, 5, 4095, *(int(x) for x in runs[7][:20])]
    qs = frame(spark, [(i, a, a + 3) for i, a in enumerate(lo)], "qid long, lo long, hi long")
    got = {(r.run_id, r.qid): (r.pred, r.succ) for r in profile.neighbours(kk, qs, strategy).collect()}
    assert got == {(r, i): (max((int(c) for c in cs if c < a), default=None), min((int(c) for c in cs if c >= a), default=None)) for r, cs in runs.items() for i, a in enumerate(lo)}


def test_runs_without_samples_or_filters_lose_nothing(spark):
    """A run that no empty sample meets gets a default filter, and a run without any filter survives."""
    rows = frame(spark, [(0, 10), (0, 20), (1, 5000)], "run_id long, code long")
    qs = frame(spark, [(1, 10, 12), (2, 5000, 5000), (3, 19, 21), (4, 30, 40)], "qid long, lo long, hi long")
    overlap = store.overlapping(store.catalog(rows), qs, K16)
    full = frame(spark, [(10, 10), (5000, 5000)], "lo long, hi long")
    for sample in (full, frame(spark, [], "lo long, hi long")):
        built = construct.build_run_filters(rows, sample, 16)
        kept = store.survivors(overlap, filters.probe(built, overlap, 16))
        assert {r.qid: r.first_key for r in store.closed_seek(rows, kept).collect()} == {1: 10, 2: 5000, 3: 20}
    lone = store.survivors(overlap, filters.probe(built.where("run_id = 0"), overlap, 16))
    assert {r.qid: r.first_key for r in store.closed_seek(rows, lone).collect()} == {1: 10, 2: 5000, 3: 20}
    designs = filters.hybrid_design(search.choose_design(frame(spark, [], "run_id long, l1 int, l2 int, bloom long, p double, exp_fpr double")), frame(spark, [(0, 40), (1, 20)], "run_id long, m long"), 16)
    assert {r.run_id for r in filters.build(rows, 16, designs).collect()} == {0, 1}
    nothing = frame(spark, [], "run_id long, code long")
    assert construct.build_run_filters(nothing, full, 16).count() == 0 and store.closed_seek(nothing, overlap).count() == 0


def test_every_kind_keeps_all_keys_at_every_budget(spark):
    rng = np.random.default_rng(5)
    codes = np.unique(rng.integers(0, 1 << 30, 2000))
    lo = np.r_[codes[:300], rng.integers(0, 1 << 30, 300)]
    hi = np.minimum(lo + rng.integers(0, 5000, len(lo)), (1 << 30) - 1)
    rows = compare.compare(one_run(spark, codes), {0: (30, (lo[300:], hi[300:]), (lo, hi))}, [6, 10, 18]).collect()
    assert len(rows) == 3 * len(compare.KINDS) and all(r.false_negatives in (0, None) for r in rows)
    assert any(r.fpr is None for r in rows if r.filter == "unique_prefix" and r.bpk == 6) and all(r.stored_bpk <= r.bpk * 1.05 + 0.5 for r in rows if r.fpr is not None)
    best = {(r.bpk, r.filter): r.fpr for r in rows if r.fpr is not None}
    assert all(best[b, "hybrid"] <= best[b, "single"] + 0.02 for b in (6, 10, 18))


def test_dyadic_probe_is_the_descent():
    rng = np.random.default_rng(4)
    codes = np.unique(rng.integers(0, 1 << 16, 60))
    blooms = [filters.Bloom.of(codes >> (16 - x), 400) for x in range(9, 17)]
    lo = rng.integers(0, 1 << 16, 300)
    hi = np.minimum(lo + rng.integers(0, 300, 300), (1 << 16) - 1)

    def holds(level, block):
        if level >= 9 and not blooms[level - 9].test(np.array([block]))[0]:
            return False
        return level == 16 or holds(level + 1, 2 * block) or holds(level + 1, 2 * block + 1)

    def cover(a, b, level=0, block=0):
        first, last = block << (16 - level), ((block + 1) << (16 - level)) - 1
        if last < a or first > b:
            return []
        return [(level, block)] if a <= first and last <= b else cover(a, b, level + 1, 2 * block) + cover(a, b, level + 1, 2 * block + 1)

    maybe, probes = filters.probe_dyadic(blooms, 16, lo, hi)
    assert [any(holds(*x) for x in cover(int(a), int(b))) for a, b in zip(lo, hi, strict=True)] == maybe.tolist()
    assert all(m for a, b, m in zip(lo, hi, maybe, strict=True) if ((codes >= a) & (codes <= b)).any()) and (probes > 0).all()


@pytest.mark.parametrize("kind", sorted(filters.BUILDERS))
def test_membership_filters_follow_their_formula(kind):
    rng = np.random.default_rng(6)
    values, absent = np.unique(rng.integers(0, 1 << 40, 20_000)), rng.integers(1 << 40, 1 << 41, 60_000)
    f = filters.BUILDERS[kind].of(values, 10 * len(values))
    assert f.test(values).all()
    want = amq.KINDS[kind].fpr(f.m / len(values)) if kind != "xor" else 2.0**-f.bits
    assert abs(f.test(absent).mean() - want) < 0.004


def test_wide_filters_take_the_wide_hash():
    from rangegate.functions.hashes import P, hash_pair

    first, step = hash_pair(np.arange(100_000), 8 * P)
    assert first.max() > 7 * P and (step >= 1).all() and step.max() < 8 * P


def test_counts_of_a_counting_filter_are_upper_bounds():
    rng = np.random.default_rng(8)
    prefixes = rng.integers(0, 400, 2000)
    f = filters.CountingBloom.of(prefixes, 16_000, 4)
    truth = np.bincount(prefixes, minlength=400)
    got = f.count(np.arange(400))
    assert (got >= np.minimum(truth, f.top)).all() and got.max() <= f.top == 15 and f.range_count(10, 12) >= np.minimum(truth[10:13], 15).sum()


@pytest.mark.parametrize("depth", [3, 8, 13, 24, 40])
def test_trie_with_tails(depth):
    prefixes = np.unique(np.random.default_rng(depth).integers(0, 1 << depth, 500))
    for dense in (0, 1):
        blob = trie.encode_tails(prefixes, depth, dense)
        assert (trie.decode_tails(blob) == prefixes).all()
    if depth == 40:
        assert trie.stored_bits(trie.encode_tails(prefixes, depth, 0)) < trie.exact_bits(prefixes, depth, 0) + 2000


def test_printed_and_summed_forms_of_the_dual_rate(spark):
    rows = {r.form: r.exp_fpr for r in engine.QUERIES["dual_forms"](spark, SF).collect()}
    assert abs(rows["sum"] - rows["product"]) < 2e-9 and 0 <= rows["printed"] <= 1 and abs(rows["printed"] - rows["product"]) > 1e-6


def test_rates_of_real_filters_are_the_expected_ones(spark):
    ks = workload.SETS["n62"]
    kk = workload.keys(spark, SF, "n62").persist()
    rows = compare.design_map(spark, kk, workload.split_queries(spark, kk, ks, 300), 62, 10, "single").persist()
    error = compare.model_error(rows).first()
    assert error.designs == 62 and error.mean_gap < 0.02 and error.regret < 0.05 and error.correlation > 0.99


def test_reads_touch_surviving_folders_only(spark):
    path, overlap, answers, _ = engine.written(spark, SF, "ts", "uniform")
    kept = store.survivors(overlap, answers)
    plan = store.read_runs(spark, path, kept)._jdf.queryExecution().executedPlan().toString()
    assert "dynamicpruning" in plan.lower()
    sizes = store.file_bytes(spark, path).collect()
    assert len(sizes) >= 1 and all(r.bytes > 0 for r in sizes)
    costs = measures.io_costs(overlap, kept, store.file_bytes(spark, path)).first()
    assert costs.bytes_read + costs.bytes_avoided == costs.bytes_overlapping and costs.reads <= costs.overlaps


def test_doubles_keep_their_order(spark):
    values = [float("-inf"), -1e300, -1.5, -5e-324, -0.0, 5e-324, 2.5, 1e300, float("inf")]
    codes = [r.c for r in frame(spark, [(i, v) for i, v in enumerate(values)], "i int, v double").select("i", keys.double_code("v").alias("c")).orderBy("i").collect()]
    assert codes == sorted(codes) and len(set(codes)) == len(codes)


def string_run(n=300, width=12, seed=0):
    rng = np.random.default_rng(seed)
    held = np.unique(strings.padded([bytes(rng.integers(97, 101, int(rng.integers(1, width + 1)), dtype=np.uint8)) for _ in range(n)], width))
    low = [int(x) for x in rng.integers(0, len(held), 200)]
    numbers = strings.numbers(held)
    top = (1 << (8 * width)) - 1
    lo = [min(top, numbers[i] + int(rng.integers(0, 1 << 30))) for i in low]
    hi = [min(top, a + int(rng.integers(0, 1 << 34))) for a in lo]
    return held, *(strings.padded([x.to_bytes(width, "big") for x in xs], width) for xs in (lo, hi))


def test_string_filters_lose_no_key():
    held, lo, hi = string_run()
    numbers, a, b = (strings.numbers(x) for x in (held, lo, hi))
    truth = np.array([any(x <= k <= y for k in numbers) for x, y in zip(a, b, strict=True)])
    for design in ((0, 70, 3000), (12, 0, 0), (16, 70, 3000), (21, 93, 3000)):
        assert not (truth & ~strings.answer(held, design, lo, hi)).any(), design
    maybe, bpk = strings.unique_answer(held, lo, hi)
    assert not (truth & ~maybe).any() and bpk > 0


def test_string_evidence_counts_prefixes_and_regions():
    held, lo, hi = string_run(200, 6, 3)
    n, numbers = strings.prefix_counts(held), strings.numbers(held)
    assert n[1:].tolist() == [len({x >> (48 - l) for x in numbers}) for l in range(1, 49)]
    e = strings.StringEvidence(held, lo, hi, list(range(1, 49)))
    for l1 in (0, 9, 16, 30):
        probes = e.probes(l1)
        held_prefixes = {x >> (48 - l1) for x in numbers}
        for i, (a, b) in enumerate(zip(e.low, e.high, strict=True)):
            for j, l2 in enumerate(range(l1 + 1, 49)):
                ends = {a >> (48 - l1), b >> (48 - l1)} & held_prefixes
                want = sum(min(b >> (48 - l2), ((p + 1) << (l2 - l1)) - 1) - max(a >> (48 - l2), p << (l2 - l1)) + 1 for p in ends)
                assert math.isclose(probes[i, j], want, rel_tol=1e-12), (l1, l2)


def test_a_short_key_and_its_padded_twin_cannot_be_told_apart():
    held = np.unique(strings.padded([b"ab", b"zz"], 4))
    twin = strings.padded([b"ab\0"], 4)
    assert strings.answer(held, (0, 32, 400), twin, twin).all()


def test_string_report(spark):
    held, lo, hi = string_run()
    kk = frame(spark, [(0, bytes(x)) for x in held], "run_id long, code binary")
    qs = frame(spark, [(bytes(a).ljust(12, b"\0"), bytes(b).ljust(12, b"\0")) for a, b in zip(lo, hi, strict=True)], "lo binary, hi binary")
    rows = {r.kind: r for r in strings.string_report(kk, qs, 12, 14).collect()}
    assert rows.keys() == {"hybrid", "single", "trie", "unique_prefix"} and all(r.false_negatives == 0 for r in rows.values())
    assert rows["hybrid"].exp_fpr <= min(rows["single"].exp_fpr, rows["trie"].exp_fpr) + 1e-9 and abs(rows["hybrid"].exp_fpr - rows["hybrid"].obs_fpr) < 0.1


def _grown(spark, folder, copies: int) -> str:
    """Events and line items repeated with shifted keys, which outgrow the bits of their codes."""
    for name, key in (("events", "user_id"), ("lineitem", "l_orderkey")):
        rows = spark.read.parquet(f"/root/testdata/sf0.001/{name}.parquet")
        step = rows.agg(F.max(key)).first()[0] + 1
        shift = 1500 if name == "events" else 200_000
        grown = rows.crossJoin(spark.range(copies).withColumnRenamed("id", "copy__")).withColumn(key, F.col(key) + F.col("copy__") * max(step, shift))
        if name == "events":
            grown = grown.withColumn("event_id", F.col("event_id") + F.col("copy__") * 100_000)
        grown.drop("copy__").write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["n_l_user_ts", "n_l_line", "prefix_density", "best_hybrid_line_uniform", "best_single_line_uniform", "best_trie_user_ts_split", "design_space_hybrid_user_ts_split", "best_dual_coarse_user_ts"])
def test_codes_beyond_their_bits_equal_the_oracle(spark, tmp_path, name):
    folder = _grown(spark, tmp_path, 6)
    con = duckdb.connect()
    con.sql("set timezone = 'UTC'")
    for table in ("events", "lineitem"):
        con.sql(f"create view {table} as select * from '{folder}/{table}.parquet/*.parquet'")
    rounded = lambda rows: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows)
    assert rounded(tuple(r) for r in engine.QUERIES[name](spark, folder).collect()) == rounded(con.sql(engine.ORACLES[name]).fetchall())


def test_filters_fit_codes_beyond_their_bits(spark, tmp_path):
    folder = _grown(spark, tmp_path, 6)
    rows = experiments._map(spark, folder, "user_ts", "hybrid", 60).collect()
    assert max(r.l2 for r in rows) == 55  # user ids up to 7,500 take 13 bits
    assert all(0 <= r.exp_fpr <= 1 and 0 <= r.obs_fpr <= 1 for r in rows)


def test_window_strategy_never_walks_a_shrinking_frame(spark):
    """Spark adds a frame up row by row if its start moves, which costs the square of a run."""
    kk = frame(spark, [(0, i * 3) for i in range(50)], "run_id long, code long")
    asked = frame(spark, [(i, i, i + 1) for i in range(0, 150, 7)], "qid long, lo long, hi long")
    found = profile.neighbours(kk, asked, "union_window")
    assert "unboundedfollowing" not in found._jdf.queryExecution().toString().lower()
    assert sorted(found.collect()) == sorted(profile.neighbours(kk, asked, "broadcast").collect())


def test_rates_of_many_queries_in_parts(monkeypatch):
    rng = np.random.default_rng(3)
    codes = np.unique(rng.integers(0, 1 << 20, 400))
    lo = np.sort(rng.integers(0, (1 << 20) - 70, 900))
    hi = lo + rng.integers(0, 60, 900)
    whole = {k: construct.tune_run(codes, lo, hi, 20, 10, k, binned=b)[0] for k, b in (("hybrid", True), ("single", False), ("dual", True))}
    monkeypatch.setattr(construct, "PART", 64)
    for (kind, rates), binned in zip(whole.items(), (True, False, True), strict=True):
        parts = construct.tune_run(codes, lo, hi, 20, 10, kind, binned=binned)[0]
        assert [r[:4] for r in parts] == [r[:4] for r in rates] and np.allclose([r[5] for r in parts], [r[5] for r in rates], atol=1e-12)


def test_samples_beyond_fifty_thousand(spark):
    """As many queries as a store of real bounds has; none is left out, none is refused."""
    keys_ = spark.range(0, 4_000_000, 997).select(F.lit(0).cast("long").alias("run_id"), F.col("id").alias("code"))
    asked = spark.range(60_000).select((F.col("id") * 61).alias("lo"), (F.col("id") * 61 + 5).alias("hi"))
    assert len(construct.shared_sample(asked).value[0]) == 60_000
    assert construct.chosen(keys_, asked, 22, 10, "single").count() == 1


@pytest.mark.parametrize("name", ["amq_kinds", "bloom_fpr_table", "chernoff_table", "cover_ts", "dyadic_cover_ts", "dyadic_recursive", "dyadic_table_function", "enc_n62", "enc_u62", "lateral_cover", "min_bits_table"])
def test_given_tables_are_read_and_decide_the_result(spark, name):
    found = engine.QUERIES[name](spark, SF)
    assert any(f.endswith(("events.parquet", "customer.parquet")) for f in found.inputFiles())
    test_query_equals_oracle(spark, name)


def _run_of(n: int, bits: int):
    rng = np.random.default_rng(5)
    codes = np.unique(rng.integers(0, 1 << bits, n))
    lo = np.sort(rng.integers(0, (1 << bits) - 70, 200))
    return codes, construct.Evidence(codes, lo, lo + rng.integers(0, 60, 200), bits), construct.key_prefix_counts(codes, bits)


def test_dual_map_builds_each_filter_of_a_tile_once(monkeypatch):
    """A filter depends on its length only: it was built again for every other length."""
    bits, m = 30, 20_000
    (codes, e, n), built, build = _run_of(2000, bits), [], filters.Bloom._set
    monkeypatch.setattr(filters.Bloom, "_set", staticmethod(lambda *a: built.append(1) or build(*a)))
    got = {(r[0], r[1]): r[2:] for t in compare.tiles(bits) for r in compare.dual_designs(codes, e, n, m, 0.4, t, 1 << 12)}
    assert sorted(got) == [(a, b) for a in range(1, bits) for b in range(a + 1, bits + 1)] and len(built) < len(got) // 2
    for a, b in ((1, 2), (7, 30), (18, 19), (20, 29)):
        two = [filters.Bloom.of(codes >> (bits - x), y) for x, y in ((a, 8000), (b, 12_000))]
        assert (got[a, b][1] == filters.probe_levels(two, [a, b], bits, e.lo, e.hi, 1 << 12)[0]).all()


def test_hybrid_map_hashes_the_prefixes_of_a_length_once(monkeypatch):
    """Filters of one length differ in size only: their prefixes were hashed again for every depth of the trie."""
    bits, m = 30, 20_000
    (codes, e, n), hashed, pair = _run_of(2000, bits), [], filters.raw_pair
    want = [(a, b, r, filters.Bloom.of(codes >> (bits - b), size) if b else None) for a, b, _, size, _, r in construct.hybrid_rates(e, n, construct.trie_memory(n, bits)[0], m, range(1, bits + 1))]
    monkeypatch.setattr(filters.Bloom, "test", lambda self, x: np.ones(len(x), bool))
    monkeypatch.setattr(filters, "raw_pair", lambda x, size: hashed.append(len(x)) or pair(x, size))
    made, build = {}, filters.Bloom.of_hashes
    monkeypatch.setattr(filters.Bloom, "of_hashes", staticmethod(lambda f, s, size: made.setdefault((len(f), size), build(f, s, size))))
    got = [r[:3] for b in range(bits, -1, -1) for r in compare.trie_designs(codes, e, n, m, "hybrid", b, 1 << 12)]
    assert sorted(got) == sorted(w[:3] for w in want) and sum(hashed) == n[1:].sum()
    assert all((made[n[b], f.m].data == f.data).all() for _, b, _, f in want if f and n[b] != n[b - 1] and (b == bits or n[b] != n[b + 1]))


def test_filters_of_all_sizes_come_from_one_pass_over_the_keys(monkeypatch):
    """A map of designs builds a thousand filters: places need no division and no second hash, and are those of the formula."""
    values = np.unique(np.r_[np.random.default_rng(1).integers(0, 1 << 62, 70_000), 0, hashes.P - 1, hashes.P, hashes.P**2, (1 << 62) - 1])
    (a, b, c), p = hashes._seeded(101), hashes.P
    for x in values[::5000].tolist() + [0, p, p * p]:
        t = ((a * (x % p)) % p + (b * (x // p % p)) % p + c) % p
        t = (a * ((t * t + c) % p) + b) % p
        assert hashes.mix_numpy(101, np.array([x]))[0] == (t * t + t * c + a) % p
    pair = filters.prefix_hashes(values, 62, 62)
    for m in (1, 2, 999, 500_000):
        first, step = hashes.hash_pair(values, m)
        f, bits = filters.Bloom.of_hashes(*pair, m), np.zeros(m, bool)
        for i in range(f.h):
            bits[(first + i * step) % m] = True
        monkeypatch.setattr(filters, "UNPACKED", 0)
        assert (f.data == np.packbits(bits)).all() and (filters.Bloom.of_hashes(*pair, m).data == f.data).all() and f.test(values).all()
        monkeypatch.undo()


def test_a_large_run_is_compared_in_little_memory():
    """Filters of all kinds beside the keys: several times the keys were held for each hash, place, region and bit."""
    rng = np.random.default_rng(2)
    codes = np.unique(rng.integers(0, 1 << 24, 2_000_000))
    lo = np.sort(rng.integers(0, (1 << 24) - 9, 200))
    for kind in compare.KINDS:
        compare.make(kind, codes[:50_000], lo, lo + 4, 24, 12)  # imports and caches
        tracemalloc.start()
        f, _ = compare.make(kind, codes, lo, lo + 4, 24, 12)
        filters.answer(f, 24, lo, lo + 4)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        # a byte a bit of a small filter, and the prefixes of a trie twice
        assert peak < 3.5 * codes.nbytes, kind


def test_packed_runs_are_whole(spark):
    """Pieces of runs hold every key once, whatever the gaps."""
    rows = [(r, x) for r, step in ((0, 1), (3, 300), (4, 70_000), (9, 1 << 40)) for x in range(0, 1000 * step, step)] + [(3, 300), (9, (1 << 62) + 5), (9, 0)]
    pieces = compare.packed(frame(spark, rows, "run_id long, code long").repartition(3)).toArrow()
    for r in (0, 3, 4, 9):
        got = compare.unpacked(pieces.filter(pc.equal(pieces.column("run_id"), r)).to_batches())
        assert got.tolist() == sorted({x for i, x in rows if i == r})
