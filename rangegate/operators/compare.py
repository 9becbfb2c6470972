"""Filters against each other and against their model: rates of all designs, of all filter kinds, and what they cost.

All of it runs on bounded runs: one run is one group, or one broadcast behind a check of its size; designs, data sets and
budgets are spread over tasks.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.functions.hashes import P
from rangegate.operators import construct, filters, trie

MAX_RUN_KEYS = 20_000_000
MAX_BOUNDS = 3_200_000
#: Lengths of a block of dual designs.
SIDE = 9
#: Keys of a packed piece of a run.
PIECE = 1 << 17
MAP = "l1 int, l2 int, exp_fpr double, obs_fpr double"
KINDS = ("hybrid", "dual", "single", "whole_key", "hierarchical", "hierarchical_equal", "hierarchical_sampled", "unique_prefix", "unique_prefix_real", "unique_prefix_hash", "unique_prefix_mixed")
COMPARED = "cell int, bpk double, filter string, l1 int, l2 int, exp_fpr double, n_empty long, fpr double, false_negatives long, stored_bpk double, trie_share double, avg_probes double, max_probes long, avg_visits double, build_ms double, probe_ms double"


def one_run(keys: DataFrame) -> np.ndarray:
    """The sorted codes of a run, which is bounded."""
    rows = keys.select("code").distinct().limit(MAX_RUN_KEYS + 1).toArrow()
    if rows.num_rows > MAX_RUN_KEYS:
        raise ValueError(f"a run holds {MAX_RUN_KEYS} keys at most; cut it with balanced_runs")
    return np.sort(rows.column("code").to_numpy())


def bounds(queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    rows = queries.select("lo", "hi").orderBy("lo", "hi").limit(construct.MAX_SAMPLE + 1).toArrow()
    if rows.num_rows > construct.MAX_SAMPLE:
        raise ValueError(f"a sample holds {construct.MAX_SAMPLE} queries at most")
    return rows.column("lo").to_numpy(), rows.column("hi").to_numpy()


def tiles(bits: int) -> list[tuple[range, range]]:
    """Blocks of l1 and l2 of dual designs, the deepest first; each pair l1 < l2 is in one."""
    blocks = [range(a, min(a + SIDE, bits + 1)) for a in range(1, bits + 1, SIDE)][::-1]
    return [(x, y) for i, y in enumerate(blocks) for x in blocks[i:]]


def dual_designs(codes: np.ndarray, e: construct.Evidence, n: np.ndarray, m: int, split: float, tile: tuple[range, range], cap: int) -> Iterator[tuple]:
    """l1, l2, expected rate and answers of the dual designs of a tile. Each filter is built once, and the first one asked once."""
    bits, m1, blooms = e.bits, int(np.floor(m * split)), {}

    def bloom(length: int, size: int) -> filters.Bloom:
        if (length, size) not in blooms:
            blooms[length, size] = filters.Bloom.of_prefixes(codes, bits, length, size)
        return blooms[length, size]

    for l1 in tile[0]:
        seconds = [x for x in tile[1] if x > l1]
        rates = {r[1]: r[5] for r in construct.dual_rates(e, n, m, range(1, bits + 1), (split,), [l1], alone=False)}
        asked = filters.Asked.of(len(e)).level(bloom(l1, m1), l1, bits, e.lo, e.hi, cap) if seconds else None
        for l2 in seconds:
            yield l1, l2, rates[l2], asked.level(bloom(l2, m - m1), l2, bits, e.lo, e.hi, cap).maybe


def trie_designs(codes: np.ndarray, e: construct.Evidence, n: np.ndarray, m: int, kind: str, l2: int, cap: int) -> Iterator[tuple]:
    """l1, l2, expected rate and answers of the ``single`` or ``hybrid`` designs of one Bloom length, whose prefixes are hashed once."""
    bits, hashed, tries = e.bits, None, construct.trie_memory(n, e.bits)[0]
    for l1, b, _, size, _, rate in construct.hybrid_rates(e, n, tries, m, range(1, bits + 1), None if kind == "hybrid" else [0], binned=kind == "hybrid"):
        if b != l2:
            continue
        own = None
        if l2 and size <= P:
            hashed = hashed or filters.prefix_hashes(codes, bits, l2)
            own = filters.Bloom.of_hashes(*hashed, size)
        elif l2:
            own = filters.Bloom.of_prefixes(codes, bits, l2, size)
        yield l1, l2, rate, filters.probe_hybrid(filters.prefixes_of(codes, bits, l1), l1, own, l2, bits, e.lo, e.hi, cap)[0] if l1 else filters.probe_levels([own], [l2], bits, e.lo, e.hi, cap)[0]


def design_map(spark: SparkSession, keys: DataFrame, queries: DataFrame, bits: int, bpk: float, kind: str = "hybrid", split: float = 0.5, cap: int = 1 << 12) -> DataFrame:
    """l1, l2, exp_fpr, obs_fpr of every design of a kind (``single``, ``hybrid``, ``dual`` at one split), each one built and probed.

    Lengths l2, the deepest first, are dealt to tasks; of dual designs, whose two filters depend on one length each, blocks of l1 and
    l2. The probes of a query stop at ``cap`` with a yes.
    """
    shared = spark.sparkContext.broadcast((one_run(keys), *bounds(queries)))
    units = tiles(bits) if kind == "dual" else range(bits, -1, -1) if kind == "hybrid" else range(1, bits + 1)

    def run(batches: Iterator) -> Iterator:
        codes, lo, hi = shared.value
        m, n = int(np.floor(len(codes) * bpk)), construct.key_prefix_counts(codes, bits)
        e, rows = construct.Evidence(codes, lo, hi, bits), []
        for x in (x for b in batches for x in b.column("id").to_pylist()):
            found = dual_designs(codes, e, n, m, split, units[x], cap) if kind == "dual" else trie_designs(codes, e, n, m, kind, units[x], cap)
            rows += [(l1, l2, rate, float(maybe.mean())) for l1, l2, rate, maybe in found]
        l1, l2, expected, observed = zip(*rows, strict=True) if rows else ((),) * 4
        yield pa.RecordBatch.from_arrays([pa.array(l1, pa.int32()), pa.array(l2, pa.int32()), pa.array([round(x, 9) for x in expected], pa.float64()), pa.array([round(x, 9) for x in observed], pa.float64())], ["l1", "l2", "exp_fpr", "obs_fpr"])

    return spark.range(0, len(units), 1, len(units) if kind != "single" else 1).mapInArrow(run, MAP)


def model_error(design_rates: DataFrame) -> DataFrame:
    """Gap of expected and observed rates over all designs, and the regret of the design that the model picks."""
    gap = F.abs(F.col("exp_fpr") - F.col("obs_fpr"))
    picked = F.min_by("obs_fpr", F.struct("exp_fpr", -F.col("l1"), -F.col("l2")))
    out = design_rates.agg(F.count("*").alias("designs"), F.avg(gap).alias("mean_gap"), F.max(gap).alias("max_gap"), F.corr("exp_fpr", "obs_fpr").alias("correlation"), F.min("exp_fpr").alias("best_expected"), picked.alias("picked_observed"), F.min("obs_fpr").alias("best_observed"))
    return out.withColumn("regret", F.col("picked_observed") - F.col("best_observed"))


def design_matrix(rates: DataFrame, lengths: list[int], value: str = "exp_fpr") -> DataFrame:
    """One row a depth l1, one column a Bloom length; designs that do not fit are null."""
    return rates.groupBy("l1").pivot("l2", lengths).agg(F.round(F.first(value), 9))


def _levels(codes: np.ndarray, bits: int, lengths: list[int], sizes: list[int], kind: str = "levels") -> dict:
    blooms = [filters.Bloom.of_prefixes(codes, bits, x, s) for x, s in zip(lengths, sizes, strict=True)]
    return {"kind": kind, "lengths": lengths, "depth": 0, "m": [b.m for b in blooms], "h": [b.h for b in blooms], "words": [b.packed() for b in blooms], "trie": b"", "aux": b"", "n_keys": len(codes), "bits": sum(b.m for b in blooms)}


def _unique(codes: np.ndarray, bits: int, real: int, hashed: int) -> dict:
    regions, marks, size = filters.unique_blob(codes, bits, real, hashed)
    return {"kind": "unique_prefix", "lengths": [], "depth": 0, "m": [], "h": [real, hashed], "words": [], "trie": regions, "aux": marks, "n_keys": len(codes), "bits": size}


def make(kind: str, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, bits: int, bpk: float) -> tuple[dict | None, tuple | None]:
    """Filter row of a kind at a budget, tuned on a sample, and its design; None where the budget does not hold it."""
    m = int(np.floor(len(codes) * bpk))
    if kind in ("hybrid", "single", "dual"):
        _, best, told = construct.tune_run(codes, lo, hi, bits, bpk, kind)
        return construct.built(codes, bits, kind, best, told), best
    if kind == "whole_key":
        return _levels(codes, bits, [bits], [m]), None
    if kind.startswith("hierarchical"):
        lengths, shares = filters.dyadic_levels(hi - lo + 1, bits, m, {"hierarchical": "last", "hierarchical_equal": "equal", "hierarchical_sampled": "sampled"}[kind])
        return _levels(codes, bits, lengths, [max(1, int(m * s)) for s in shares], "dyadic"), None
    best = filters.best_suffix(codes, bits, m, lo, hi)
    if best is None:
        return None, None
    spare = max(0, (m - filters.unique_prefix_bits(codes, bits, filters.unique_lengths(codes, bits), 0)) // len(codes))
    real, hashed = {"unique_prefix": best[:2], "unique_prefix_real": (min(8, spare), 0), "unique_prefix_hash": (0, min(8, spare)), "unique_prefix_mixed": (min(8, spare) // 2, min(8, spare) - min(8, spare) // 2)}[kind]
    return _unique(codes, bits, int(real), int(hashed)), None


def packed(keys: DataFrame) -> DataFrame:
    """run_id, n, first, width, gaps: pieces of runs of up to ``PIECE`` keys, in the order of the keys and with the bytes that a gap takes."""

    def run(batches: Iterator) -> Iterator:
        held, size = [], 0

        def pieces() -> pa.RecordBatch:
            run_id, code = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in ("run_id", "code"))
            rows = []
            for r in np.unique(run_id).tolist():
                own = np.unique(code[run_id == r])
                gaps = np.diff(own)
                width = next(w for w in (1, 2, 4, 8) if int(gaps.max(initial=0)) < 1 << (8 * w - (w == 8)))
                rows.append((r, len(own), int(own[0]), width, gaps.astype(f"<u{width}").tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)], ["run_id", "n", "first", "width", "gaps"])

        for b in batches:
            held, size = [*held, b] if b.num_rows else held, size + b.num_rows
            if size >= PIECE:
                yield pieces()
                held, size = [], 0
        if held:
            yield pieces()

    return keys.select("run_id", "code").mapInArrow(run, "run_id long, n long, first long, width int, gaps binary")


def unpacked(batches: list[pa.RecordBatch]) -> np.ndarray:
    """The sorted distinct codes of some pieces."""
    codes, at = np.empty(sum(int(n) for b in batches for n in b.column("n").to_pylist()), np.int64), 0
    for b in batches:
        for i in range(b.num_rows):
            n, first, width = (b.column(c)[i].as_py() for c in ("n", "first", "width"))
            codes[at] = first
            gaps = np.frombuffer(b.column("gaps")[i].as_buffer(), f"<u{width}")
            np.cumsum(gaps.astype(np.int64), out=codes[at + 1 : at + n])  # unsigned ones of 64 bits would be summed as doubles
            codes[at + 1 : at + n] += first
            at += n
    codes.sort()
    return codes if (new := trie.starts(codes, 0)).all() else codes[new]


def compare(keys: DataFrame, cells: dict[int, tuple[int, tuple, tuple]], budgets: list[float], kinds: tuple = KINDS) -> DataFrame:
    """Every kind at every budget for each cell: ``keys(run_id = cell, code)``; ``cells`` gives key bits, sample and test bounds.

    A cell at a budget is one task. It gets the keys packed and holds them once, beside one filter at a time.

    Sizes are those of what is stored. A kind that a budget does not hold has null rates.
    """
    limit = sum(len(x) for _, a, b in cells.values() for x in (*a, *b))
    if limit > MAX_BOUNDS:
        raise ValueError("too many queries to broadcast")
    shared, ids = keys.sparkSession.sparkContext.broadcast(cells), sorted(cells)
    unit = F.array_position(F.array(*[F.lit(x).cast("long") for x in ids]), F.col("run_id")) - 1 + F.col("budget") * len(ids)
    spread = packed(keys).withColumn("budget", F.explode(F.sequence(F.lit(0), F.lit(len(budgets) - 1)))).withColumn("unit", unit.cast("int"))

    def run(batches: Iterator) -> Iterator:
        batches = list(batches)
        if not sum(b.num_rows for b in batches):
            return
        cell, bpk = next((b.column("run_id")[0].as_py(), float(budgets[b.column("budget")[0].as_py()])) for b in batches if b.num_rows)
        bits, sample, (lo, hi) = shared.value[cell]
        codes, rows = unpacked(batches), []
        del batches
        empty = np.searchsorted(codes, lo) == np.searchsorted(codes, hi, side="right")
        for kind in kinds:
            f, began = None, time.perf_counter()  # one filter is held at a time
            f, best = make(kind, codes, *sample, bits, bpk)
            built = time.perf_counter()
            l1, l2, expected = (best[0], best[1], best[5]) if best else (None, None, None)
            if f is None:
                rows.append((cell, bpk, kind, l1, l2, None, int(empty.sum()), None, None, filters.minimum_bits(codes, bits), None, None, None, None, None, None))
                continue
            maybe, visits, probes = filters.answer(f, bits, lo, hi)
            done = time.perf_counter()
            in_trie = f["bits"] - sum(f["m"])
            rate = float(maybe[empty].mean()) if empty.any() else None
            rows.append((cell, bpk, kind, l1, l2, expected, int(empty.sum()), rate, int((~maybe & ~empty).sum()), f["bits"] / len(codes), in_trie / f["bits"], float(probes.mean()), int(probes.max(initial=0)), float(visits.mean()), (built - began) * 1e3, (done - built) * 1e3))
        types = {"cell": pa.int32(), "bpk": pa.float64(), "filter": pa.string(), "l1": pa.int32(), "l2": pa.int32(), "n_empty": pa.int64(), "false_negatives": pa.int64(), "max_probes": pa.int64()}
        names = [x.split()[0] for x in COMPARED.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array(x, types.get(c, pa.float64())) for c, x in zip(names, zip(*rows, strict=True), strict=True)], names)

    units = len(ids) * len(budgets)
    return spread.repartitionById(units, "unit").select("run_id", "n", "first", "width", "gaps", "budget").mapInArrow(run, COMPARED)


def sample_sweep(keys: DataFrame, queries: DataFrame, bits: int, bpk: float, sizes: list[int]) -> DataFrame:
    """For each sample size: the design it picks, its expected rate, the rate that all queries give that design, and the best one."""
    shared = keys.sparkSession.sparkContext.broadcast(bounds(queries))

    def run(key, table):
        codes = np.unique(table.column("code").to_numpy())
        lo, hi = shared.value
        order = np.argsort(filters.mix_numpy(77, lo), kind="stable")
        whole = {(r[0], r[1]): r[5] for r in construct.tune_run(codes, lo, hi, bits, bpk)[0]}
        rows = []
        for size in sizes:
            pick = order[:size]
            _, best, _ = construct.tune_run(codes, lo[pick], hi[pick], bits, bpk)
            rows.append((size, best[0], best[1], best[5], whole.get((best[0], best[1])), min(whole.values())))
        names = ("sample", "l1", "l2", "exp_fpr", "whole_fpr", "best_fpr")
        return pa.table({c: pa.array(x, pa.int32() if c in ("sample", "l1", "l2") else pa.float64()) for c, x in zip(names, zip(*rows, strict=True), strict=True)})

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, "sample int, l1 int, l2 int, exp_fpr double, whole_fpr double, best_fpr double")


def trie_sizes(keys: DataFrame, bits: int) -> DataFrame:
    """Of every depth up to 2^22 prefixes: estimated bits, exact bits without tails, stored bits with tails."""
    def run(key, table):
        codes, rows = np.unique(table.column("code").to_numpy()), []
        size, dense = construct.trie_memory(construct.key_prefix_counts(codes, bits), bits)
        for depth in range(1, bits + 1):
            prefixes = np.unique(filters._prefix(codes, bits, depth))
            blob = trie.encode_tails(prefixes, depth, int(dense[depth]))
            rows.append((depth, len(prefixes), int(size[depth]), trie.exact_bits(prefixes, depth, int(dense[depth])), trie.stored_bits(blob), bool((trie.decode_tails(blob) == prefixes).all())))
        names = ("l", "n", "estimate", "exact", "stored", "round_trip")
        return pa.table(dict(zip(names, (pa.array(x, pa.bool_() if c == "round_trip" else pa.int64()) for c, x in zip(names, zip(*rows, strict=True), strict=True)), strict=True)))

    return keys.select("run_id", "code").groupBy("run_id").applyInArrow(run, "l long, n long, estimate long, exact long, stored long, round_trip boolean")
