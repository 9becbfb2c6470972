"""The training-data operators on small fixtures with nulls, empties, ties and repeated rows, against brute force."""

import hashlib
import math
import zlib
from collections import Counter, defaultdict
from pathlib import Path
from urllib.parse import urlparse

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rangegate.llm import exact_dedup, graph, line_dedup, line_rules, lm_score, mixing, near_dedup, packing, quality, registry, substring_dedup, token_shards
from rangegate.llm.text import WordHasher
from rangegate.llm.tokens import WordBpe, default_path

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
SF = "/root/testdata/sf0.001"


def texts():
    rng = np.random.default_rng(5)
    vocab = [f"w{i}" for i in range(400)]
    base = [" ".join(rng.choice(vocab, n)) for n in (3, 4, 5, 40, 60, 120, 300)]
    out = [None, "", " \n\t ", "One two.", "one TWO.", "a b c d", *base, *[b.upper() for b in base[3:5]]]
    words = base[5].split()
    for k in (0, 40, 80):
        out.append(" ".join([*words[:k], "changed", *words[k + 1 :]]))
    out += [base[6] + " tail", base[6] + "\nother tail", "x " * 500, "lone", "lone " * 9, "Zeile\nzwei\ndrei\nvier " + base[3], "Zeile\nzwei\ndrei\nfuenf " + base[4], "É ß — «tout» 日本 'll don't"]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, None if i % 7 == 0 else "en", "s0" if i % 3 else None, None if t is None else len(t)) for i, t in enumerate(texts())]
    return spark.createDataFrame(rows, SCHEMA).withColumn("score", F.lit(1.5)).repartition(3).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_word_hashes_are_those_of_words():
    seen = defaultdict(set)
    given = [(t or "").encode() for t in texts()]
    for t, h in zip(given, WordHasher(True).each(given), strict=True):
        words = t.lower().split()
        assert len(words) == len(h)
        for w, x in zip(words, h.tolist(), strict=True):
            seen[w].add(x)
    assert all(len(v) == 1 for v in seen.values()) and len({next(iter(v)) for v in seen.values()}) == len(seen)


def test_exact_dedup(docs, empty):
    groups = defaultdict(list)
    for i, t in enumerate(texts()):
        groups[(t or "").encode().lower()].append(i)
    want = {i: (max(g), len(g)) for g in groups.values() for i in g}
    assert {r.doc_id: (r.keep_id, r.group_size) for r in exact_dedup.exact_dedup(docs).collect()} == want
    assert exact_dedup.exact_dedup(empty).count() == 0


def test_cuckoo_index_resizes_and_deletes():
    index = exact_dedup.DigestIndex(4)
    digests = [hashlib.sha256(str(i).encode()).digest() for i in range(3000)]
    for i, d in enumerate(digests):
        index.add(d, i)
    assert index.resizes and all(d in index.filter for d in digests)
    assert index.remove(digests[7]) and not index.remove(digests[7]) and digests[7] not in index.live
    index.add(digests[8], 99)
    assert index.live[digests[8]] == (99, 2)


def test_index_decides_which_rows_stay(docs, spark):
    """Copies of several tasks meet in the index, which deletes, verifies and resizes."""
    many = docs.unionByName(docs.withColumn("doc_id", F.col("doc_id") + 1000)).unionByName(spark.range(3000).selectExpr("id + 5000 as doc_id", "concat('t', id % 2500) as text", "'en' as lang", "'s' as source", "1L as n_chars", "1.0d as score")).repartition(6)
    rows = exact_dedup.digests(many).persist()
    live, stats = exact_dedup.live_digests(rows, rows.count(), bucket_rows=700, capacity=4)
    s = stats.groupBy().sum("misses", "hits", "deletions", "resizes", "false_hits").first()
    distinct = rows.select("digest").distinct().count()
    assert live.count() == distinct and s["sum(hits)"] > 0 and s["sum(deletions)"] > 0 and s["sum(resizes)"] > 0
    assert s["sum(misses)"] + s["sum(false_hits)"] == distinct
    groups = defaultdict(list)
    for r in many.collect():
        groups[(r.text or "").encode().lower()].append(r.doc_id)
    want = {i: (max(g), len(g)) for g in groups.values() for i in g}
    assert {r.doc_id: (r.keep_id, r.group_size) for r in exact_dedup.exact_dedup(many, bucket_rows=700, capacity=4).collect()} == want


def test_repeated_passages(docs, empty):
    count, given = Counter(), [(t or "").encode().split() for t in texts()]
    for w in given:
        count.update(tuple(w[i : i + 35]) for i in range(len(w) - 34))
    want = {}
    for i, w in enumerate(given):
        gone = {p for s in range(len(w) - 34) if count[tuple(w[s : s + 35])] > 1 for p in range(s, s + 35)}
        want[i] = (len(w), b" ".join(x for p, x in enumerate(w) if p not in gone))
    got = {r.doc_id: (r.n_words, bytes(r.kept)) for r in substring_dedup.repeated_passages(docs, block_bytes=500).collect()}
    assert got == want and substring_dedup.repeated_passages(empty).count() == 0


@pytest.mark.parametrize("frequent", [8, 1])
def test_near_duplicates(docs, frequent):
    sets = []
    for t in texts():
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    root = list(range(len(sets)))
    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs, frequent=frequent, block_bytes=900).collect()}
    assert got == {i: (len(s), root[i]) for i, s in enumerate(sets)}


def test_near_duplicates_of_nothing(empty):
    assert near_dedup.near_duplicates(empty).count() == 0


def test_index_keys_meet_for_all_linked_sets():
    rng = np.random.default_rng(1)
    bands = near_dedup.size_bands(75)
    for n in (2, 3, 7, 20, 90, 400):
        for often in (1, 10**9):
            for _ in range(20):
                x = np.unique(rng.integers(0, 1 << 62, n).astype(np.uint64))
                cut = int(rng.integers(0, max(1, len(x) // 7) + 1))
                y = np.unique(np.concatenate([x[cut:], rng.integers(0, 1 << 62, int(rng.integers(0, cut + 1))).astype(np.uint64)]))
                o = len(np.intersect1d(x, y))
                if len(x) > 1 and len(y) > 1 and 100 * o >= 75 * (len(x) + len(y) - o):
                    kx, ky = (np.concatenate(near_dedup.index_keys(s, 2 + (s % np.uint64(5)).astype(np.int64), often, bands)[:2]) for s in (x, y))
                    assert len(np.intersect1d(kx, ky))


def test_keys_of_one_group_are_merged(spark):
    group = [(key, node, 0) for key in range(1000, 1040) for node in range(30)]
    hub = [(2000 + i, node, 0) for i in range(50) for node in (500, 501 + i)]
    merged = near_dedup._merged(spark.createDataFrame(group + hub, "key long, node long, component long"))
    rows = [(r.key, r.node) for r in merged.collect()]
    assert sorted(r for r in rows if r[1] < 500) == [(0, node) for node in range(30)]  # each node once, not once a key
    assert sorted(r for r in rows if r[1] >= 500) == sorted(h[:2] for h in hub)  # 51 nodes would be compared that share no key


def test_variants_that_are_not_linked_meet_once_a_group(spark, monkeypatch):
    """Sixty variants of a text with few shingles of their own: similar, but linked only in part."""
    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in range(400)]
    docs = []
    for i in range(60):
        words = list(base)
        for at in rng.choice(400, 12 + i % 3, replace=False):
            words[at] = f"x{rng.integers(0, 3)}"
        docs.append((i, " ".join(words)))
    sets = [{tuple(t.split()[i : i + 5]) for i in range(396)} for _, t in docs]
    root = list(range(len(sets)))
    for i in range(len(sets)):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    seen = []
    merged = near_dedup._merged
    monkeypatch.setattr(near_dedup, "_merged", lambda paired: seen.append((paired.count(), merged(paired).count())) or merged(paired))
    got = {r.doc_id: r.component_id for r in near_dedup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == dict(enumerate(root))
    assert seen[0][0] > 10 * seen[0][1]


def test_parity_never_exceeds_the_difference():
    rng = np.random.default_rng(2)
    for n in (1, 50, 900):
        x, y = (np.unique(rng.integers(0, 1 << 62, n).astype(np.uint64)) for _ in range(2))
        differ = sum(int(a ^ b).bit_count() if a ^ b >= 0 else ((int(a ^ b)) & (1 << 64) - 1).bit_count() for a, b in zip(near_dedup.parity(x).tolist(), near_dedup.parity(y).tolist(), strict=True))
        assert differ <= len(np.setxor1d(x, y))


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(100, 101), (102, 101)], "a long, b long")
    got = {r.node: r.component for r in graph.connected_components(edges).collect()}
    assert all(got[i] == 0 for i in range(31)) and got[101] == got[102] == got[100] == 100


def test_packing_round_trip(docs, empty):
    encode = WordBpe(default_path()).encode(texts())
    rows = packing.pack(docs, default_path(), with_ids=True).collect()
    parts, sequences = defaultdict(dict), defaultdict(list)
    for r in rows:
        parts[r.doc_id][r.start] = bytes(r.ids)
        sequences[r.sequence_id].append((r.offset, r.length))
        assert r.ids_crc32 == zlib.crc32(bytes(r.ids)) and r.length * 4 == len(r.ids)
    for i, e in enumerate(encode):
        assert b"".join(parts[i][k] for k in sorted(parts[i])) == e + (1).to_bytes(4, "little")
    for s in sequences.values():
        s.sort()
        assert s[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(s, s[1:], strict=False)) and sum(n for _, n in s) <= 2048
    assert packing.pack(empty, default_path()).count() == 0


def test_packing_fills_classes_with_whole_documents():
    rng = np.random.default_rng(7)
    lengths = np.minimum(rng.lognormal(6.2, 1.1, 4000).astype(int) + 1, 20_000)
    packer = packing.HarmonicPacker(2048, 0)
    for i, n in enumerate(lengths.tolist()):
        packer.add(i, bytes(4 * n))
        assert packer.room < 2048 + 2048 and len(packer.open) <= 64
    packer.finish()
    sizes, pieces = Counter(), Counter()
    for doc_id, start, length, ids, total, sequence, offset in packer.rows:
        sizes[sequence] += length
        pieces[doc_id] += 1
    assert all(n == 2048 or n & (n - 1) == 0 for n in sizes.values()) and sum(n < 2048 for n in sizes.values()) <= 11
    fit = [i for i, n in enumerate(lengths) if n <= 2048]
    assert sum(pieces[i] == 1 for i in fit) > 0.6 * len(fit)


def test_tokenizer_agrees_with_whole_texts():
    import random

    draw = random.Random(4)
    given = ["".join(draw.choice("ab'sSTtrevmlldAZ09 \n\t!?.;’“é ÈßŒÆÿ<|>_-×÷¿日") for _ in range(draw.randint(0, 40))) for _ in range(3000)]
    bpe = WordBpe(default_path())
    assert bpe.encode(given) == [bpe._whole(t) for t in given]


def test_tokenizer_keeps_the_pieces_it_needs_beyond_its_limit():
    bpe = WordBpe(default_path(), limit=4)
    for given in (["one two three"], ["two four five", "one six"], ["a b c d e f"], ["six a", None, "x1 y2"]):
        assert bpe.encode(given) == [bpe._whole(t) for t in given]


def test_training_order(docs, empty, tmp_path):
    for n in (1, 2, 17, 1000):
        slots = token_shards.feistel(np.arange(n), n)
        assert sorted(slots) == list(range(n)) and (token_shards.feistel(slots, n, inverse=True) == np.arange(n)).all()
    rows = token_shards.training_order(docs, default_path(), width=64, shard_slots=8).persist()
    got = rows.orderBy("slot").collect()
    assert [r.slot for r in got] == list(range(len(got)))
    whole = defaultdict(dict)
    for r in got:
        ids, at = np.frombuffer(bytes(r.ids), "<u2"), 0
        for p in r.pieces:
            whole[p.doc_id][p.start] = ids[at : at + p.length]
            at += p.length
    for i, e in enumerate(WordBpe(default_path()).encode(texts())):
        assert np.concatenate([whole[i][k] for k in sorted(whole[i])]).tolist() == [*np.frombuffer(e, "<u4").tolist(), 1]
    token_shards.write_shards(rows, str(tmp_path), width=64, shard_slots=8).collect()
    assert (token_shards.read_slots(str(tmp_path), 5, 7, width=64, shard_slots=8) == np.stack([np.frombuffer(bytes(r.ids), "<u2") for r in got[5:12]])).all()
    assert token_shards.training_order(empty, default_path()).count() == 0


def test_training_order_query_writes_its_shards(spark):
    home = Path(urlparse(graph.checkpoints(spark)).path)
    before = set(home.glob("shards-*"))
    rows = token_shards.op6_training_order(spark, SF).orderBy("slot").collect()
    (folder,) = set(home.glob("shards-*")) - before
    data = b"".join(p.read_bytes() for p in sorted(folder.iterdir()))
    stride = 2 * token_shards.SEQUENCE_TOKENS
    assert len(data) == stride * len(rows) and sorted(p.name for p in folder.iterdir()) == [f"shard-{i:06d}.bin" for i in range(len(list(folder.iterdir())))]
    whole = defaultdict(dict)
    for i, r in enumerate(rows):
        part = data[i * stride : (i + 1) * stride]
        assert (r.slot, r.shard, r.byte_offset) == (i, i // token_shards.SHARD_SLOTS, i % token_shards.SHARD_SLOTS * stride) and r.ids_crc32 == zlib.crc32(part)
        ids, at = np.frombuffer(part, "<u2"), 0
        for p in r.pieces:
            whole[p.doc_id][p.start] = ids[at : at + p.length]
            at += p.length
    given = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()
    for d, e in zip(given, WordBpe(default_path()).encode([d.text for d in given]), strict=True):
        assert np.concatenate([whole[d.doc_id][k] for k in sorted(whole[d.doc_id])]).tolist() == [*np.frombuffer(e, "<u4").tolist(), 1]


def test_line_dedup(docs, empty):
    got = {r.doc_id: r for r in line_dedup.dedup_lines(docs, drop_emptied=False).collect()}
    given = texts()
    a, b = next(i for i, t in enumerate(given) if t and t.startswith("Zeile")), [i for i, t in enumerate(given) if t and t.startswith("Zeile")][1]
    assert got[a].text == given[a] and got[b].text.startswith("fuenf") and got[b].n_chars == len(got[b].text) and got[0].text is None and got[b].score == 1.5
    assert line_dedup.dedup_lines(empty).count() == 0


def test_line_rules(docs, empty, spark):
    rows = {r.doc_id: r for r in line_rules.apply_line_rules(docs).collect()}
    for i, t in enumerate(texts()):
        w = (t or "").encode().split()
        grams = Counter(tuple(w[j : j + 3]) for j in range(len(w) - 2))
        covered = {p for j in range(len(w) - 2) if grams[tuple(w[j : j + 3])] > 1 for p in range(j, j + 3)}
        assert (rows[i].n_words, rows[i].n_repeat_words) == (len(w), len(covered))
    assert line_rules.apply_line_rules(empty).count() == 0
    good = " ".join(f"word{i}" for i in range(80)) + "."
    bad = spark.createDataFrame([(1, good), (2, good.replace(" ", "*** ")), (3, good.replace(" ", " | ")), (4, good + "\nLicensed under the Apache License")], "doc_id long, text string")
    assert {r.doc_id: r.kept for r in line_rules.apply_line_rules(bad).collect()} == {1: True, 2: False, 3: False, 4: True}


def test_ordinal_fit():
    rng = np.random.default_rng(0)
    grades = rng.integers(0, 3, 600)
    rows = [np.unique(np.r_[rng.integers(100, 4000, 60), [g + 1] * (rng.random() < 0.95)]).astype(np.int32) for g in grades]
    m = quality.fit(rows[:400], grades[:400], slots=4096)
    assert m.trained and (np.diff(m.thresholds) > 0).all()
    tail = m.tails(m.scores(rows[400:]))[:, -1]
    assert ((tail >= 0.5) == (grades[400:] == 2)).mean() > 0.9
    assert not quality.fit(rows[:5], np.full(5, 2)).trained


def test_quality_edges(docs, empty, spark):
    none = spark.createDataFrame([], "doc_id long, grade int")
    assert all(r.kept for r in quality.score(docs, quality.train(docs, none)).collect())
    assert quality.keep_good(docs, quality.train(docs, none)).count() == docs.count()
    assert quality.score(empty, quality.train(empty, none)).count() == 0


def test_context_mixing(docs, empty):
    count, given = Counter(), [(t or "").encode().lower().split() + ["end"] for t in texts()]
    for i, w in enumerate(given):
        if zlib.crc32(str(i).encode()) % 5 != 1:
            count.update(w)
    n, v = sum(count.values()), len(count)
    rows = {r.doc_id: r for r in lm_score.score(docs).collect()}
    for i, w in enumerate(given):
        base = sum(math.log10((count[x] + 0.5) / (n + 0.5 * (v + 1))) for x in w)
        r = rows[i]
        assert abs(r.base_score - base) < 1e-6 and (r.n_tokens, r.n_known, r.train_tokens) == (len(w), sum(x in count for x in w), n)
        assert r.held_out == (zlib.crc32(str(i).encode()) % 5 == 1) and r.score < 0
    assert lm_score.score(empty).count() == 0


def test_scores_do_not_depend_on_blocks_or_partitions(docs, spark):
    rows = {}
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for parts, block in ((2, 900), (9, 20_000)):
        spark.conf.set("spark.sql.shuffle.partitions", parts)
        rows[parts] = {r.doc_id: tuple(r) for r in lm_score.score(docs.repartition(parts), block_bytes=block).collect()}
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert rows[2].keys() == rows[9].keys() and all(np.allclose(rows[2][i], rows[9][i], rtol=1e-9) for i in rows[2])


@pytest.mark.parametrize("rows", [[(0, "one two two")], [(0, None)], [(2, "a"), (2, "a")], [(3, "x " * 40)]])
def test_scores_of_tiny_tables(spark, rows):
    got = lm_score.score(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows) and all(np.isfinite(r.score) and r.score < 0 and np.isfinite(r.base_score) for r in got)


def test_model_beats_the_base_on_held_out_documents(spark):
    rows = lm_score.op4_context_mixing(spark, SF.replace("0.001", "0.01")).where("held_out").agg(F.sum("base_score").alias("base"), F.sum("score").alias("score")).first()
    assert rows.score > rows.base + 0.03 * abs(rows.base)


def test_block_counts_are_those_of_all_blocks():
    from rangegate.llm import blockcounts

    rng = np.random.default_rng(1)
    blocks = [np.unique(rng.integers(0, 1 << 64, 500, dtype=np.uint64) % np.uint64(1 << 62) // np.uint64(1 << 53) * np.uint64(1 << 55)) for _ in range(6)]
    counts, want = [rng.integers(0, 9, len(b)) for b in blocks], Counter()
    for b, n in zip(blocks, counts, strict=True):
        want.update(dict(zip(b.tolist(), n.tolist(), strict=True)))
    got = defaultdict(list)
    sent = [(part, i, blockcounts.unpack_keys(blockcounts.pack_keys(b[x:y], 64), 64), blockcounts.unpack(blockcounts.pack(n[x:y].astype("<u4")), "<u4")) for i, (b, n) in enumerate(zip(blocks, counts, strict=True)) for part, x, y in blockcounts.slices(b, 7)]
    for part in range(7):
        own = [s for s in sent if s[0] == part]
        if own:
            for (_, i, keys, _), found in zip(own, blockcounts.totals([s[2] for s in own], [s[3] for s in own])[2], strict=True):
                got[i] += list(zip(keys.tolist(), found.tolist(), strict=True))
    assert all(got[i] == [(k, want[k]) for k in b.tolist()] for i, b in enumerate(blocks))


def test_few_places_are_tallied_like_many():
    rng = np.random.default_rng(6)
    for n, held in ((1000, 0), (1000, 1), (1000, 200), (1000, 900)):
        place, target = rng.integers(0, n // 3, held), rng.random(held)
        some, count, hits = lm_score.tally(place, target, n, np.full(n, 7, np.int32))
        order = np.argsort(some)
        assert (some[order] == np.unique(place)).all() and (count[order] == np.bincount(place)[some[order]]).all()
        assert (hits[order] == np.bincount(place, target, n)[some[order]]).all()  # to the last bit


@pytest.mark.parametrize("shift", [0, 40])
def test_numbers_are_those_of_unique(shift):
    rng = np.random.default_rng(7)
    for n in (0, 1, 700):
        x = rng.integers(0, 90, n).astype(np.uint64) << np.uint64(shift)
        for values in (x, x + rng.integers(0, 3, n).astype(np.uint64), x.astype(np.int64)):  # values that differ in low bits only
            assert all(np.array_equal(a, b) for a, b in zip(lm_score.numbered(values), np.unique(values, return_index=True, return_inverse=True), strict=True))
            assert np.array_equal(lm_score.stable_order(values), np.argsort(values, kind="stable"))
    wide = rng.permutation(1 << 10).astype(np.uint64) + np.uint64(1 << 63)  # places take the bits that tell them apart
    assert np.array_equal(lm_score.numbered(wide)[2], np.argsort(np.argsort(wide)))


def test_keys_of_pairs_are_hashed_once_a_pair():
    t, odd = lm_score.Tokens([b"a b a b", None, b"", b"b A"]), np.uint64(0xC2B2AE3D27D4EB4F)
    assert [t.spelled[i] if i < len(t.spelled) else b"" for i in t.number.tolist()] == [b"a", b"b", b"a", b"b", b"", b"", b"", b"b", b"a", b""]
    (words, word), (pairs, pair) = t.keys(40)
    assert np.array_equal(words[word], t.hash) and len(words) == 3
    with np.errstate(over="ignore"):
        want = lm_score.mix64(t.back(t.hash, lm_score.START) * odd + t.hash) >> np.uint64(24) << np.uint64(24)
    assert np.array_equal(pairs[pair], want) and np.array_equal(pairs, np.unique(want))


def test_spelling_slots_tell_the_beginnings_of_a_byte_apart():
    begun = {(1 << k) | (byte >> (8 - k)): int(lm_score.NODES[byte, k]) for byte in range(256) for k in range(8)}
    assert len(begun) == 255 == len(set(begun.values()))


def test_spelling_counts_are_of_all_words():
    total = lm_score.spelling_counts([b"abc", b"abd", b"x"])
    assert total.sum() == lm_score.ORDERS * 8 * (4 + 4 + 2)
    _, bit, slots = lm_score.spelling_slots([b"ab"])
    raw = np.packbits(bit)
    assert raw.tobytes() == b"ab\n" and slots.max() < 1 << lm_score.SLOT_BITS


def test_mixing_meets_targets():
    rng = np.random.default_rng(0)
    tokens = rng.integers(1000, 5000, 60).astype(float)
    codes = [np.arange(60) % 5, np.arange(60) % 4, np.arange(60) % 3]
    targets = []
    for c in codes:
        have = np.bincount(c, tokens)
        share = have**0.8
        targets.append(0.4 * have.sum() * share / share.sum())
    p = mixing.rake(tokens, codes, targets, 0.4, rounds=200)
    for c, t in zip(codes, targets, strict=True):
        assert np.allclose(np.bincount(c, p * tokens), t, rtol=1e-6)


def test_mixing_on_tables_is_the_same_fit(docs):
    marked = mixing.with_cells(docs).persist()
    keys = ["source__", "lang__", "topic__"]
    one, two = ({tuple(r)[:3]: r.p__ for r in mixing.cell_probabilities(marked, max_cells=m, rounds=4).select(*keys, "p__").collect()} for m in (100_000, 0))
    assert one.keys() == two.keys() and all(math.isclose(one[k], two[k], rel_tol=1e-9) for k in one)
    rows = marked.collect()
    tokens = Counter()
    for r in rows:
        tokens[r.source__, r.lang__, r.topic__] += len((r.text or "").split())
    p = dict.fromkeys(tokens, mixing.FRACTION)
    for _ in range(4):
        for d in range(3):
            have, all_ = Counter(), Counter()
            for k, n in tokens.items():
                have[k[d]] += p[k] * n
                all_[k[d]] += n
            whole = sum(x**mixing.ALPHA for x in all_.values() if x)
            for k in tokens:
                aim = mixing.FRACTION * sum(all_.values()) * all_[k[d]] ** mixing.ALPHA / whole if all_[k[d]] else 0.0
                p[k] = min(1.0, p[k] * (aim / have[k[d]] if have[k[d]] > 0 else float(aim > 0)))
    assert p.keys() == one.keys() and all(math.isclose(p[k], one[k], rel_tol=1e-9) for k in p)


def test_mixing_edges(docs, empty):
    clash = docs.withColumns({"p": F.lit(2.0), "tokens": F.lit("x"), "topic": F.lit(1)})
    assert mixing.mix(clash).columns == clash.columns
    kept = mixing.mix(docs)
    assert kept.columns == docs.columns and kept.count() <= docs.count() and mixing.mix(empty).count() == 0


CLASHES = ["n", "p", "key", "node", "h", "own", "at", "blk", "part", "counts", "kept", "shard", "slot", "tokens", "word", "size", "first", "component", "digest", "bucket", "owner", "score", "grade", "m", "t", "seq", "length", "ids"]


@pytest.fixture(scope="module")
def odd(spark):
    """Null and repeated ids, equal rows, other columns with clashing names, and a text of two megabytes."""
    rng = np.random.default_rng(11)
    words = [f"v{i}" for i in range(3000)]
    long = "\n".join(" ".join(rng.choice(words, 12)) + "." for _ in range(28_000))
    lines = ["alpha beta gamma delta", "epsilon zeta eta theta", "iota kappa lambda mu", "nu xi omicron pi"]
    body = " ".join(rng.choice(words, 120))
    rows = [(None, "\n".join([*lines, "null one " + body[:300]])), (None, "\n".join(["other", *lines[:3], "tail"])), (None, None), (7, body), (7, body), (7, "\n".join([*lines, "seven"])), (8, long), (9, ""), (9, body + " more"), (10, " \n "), (None, body)]
    made = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], SCHEMA)
    return made.select("*", *[F.lit(f"{c}!").alias(c) for c in CLASHES]).repartition(3).persist()


def test_odd_tables_exact_and_near(odd):
    given = [(r.doc_id, (r.text or "").encode().lower()) for r in odd.collect()]
    for r in exact_dedup.exact_dedup(odd).collect():
        own = [i for i, t in given if hashlib.sha256(t).hexdigest() == r.text_sha256]
        ids = [i for i in own if i is not None]
        assert (r.group_size, r.keep_id) == (len(own), max(ids) if ids else None) and r.kept == (r.doc_id == r.keep_id)
    near = near_dedup.near_duplicates(odd, block_bytes=100_000).collect()
    assert len(near) == len(given) and sorted(r.component_id for r in near if r.n_shingles > 100 and r.n_shingles < 200) == [7, 7, 7, 7]
    kept = near_dedup.keep_one(odd)
    assert kept.columns == odd.columns and Counter(r.doc_id for r in kept.collect())[9] == 1 and sum(r.doc_id is None for r in kept.collect()) == 3


def test_odd_tables_lines(odd, spark):
    rows = line_dedup.dedup_lines(odd, drop_emptied=False)
    assert rows.columns == odd.columns
    got = {(r.doc_id, r.text) for r in rows.collect()}
    texts_ = {(r.doc_id, r.text) for r in odd.collect()}
    first = next(t for i, t in texts_ if i == 7 and t.endswith("seven"))
    assert (7, first) in got and (None, "other\ntail") in got  # the row with an id comes first, rows without one keep their own positions
    assert any(i is None and t and t.startswith("null one") for i, t in got) and (None, None) in got
    passages = {(r.doc_id, r.n_words): bytes(r.kept) for r in substring_dedup.repeated_passages(odd).collect()}
    assert passages[7, 120] == b"" and passages[9, 121] == b"more" and len(passages[8, 28_000 * 12]) > 1_000_000
    rules = line_rules.apply_line_rules(odd).collect()
    assert len(rules) == odd.count() and {r.n_words for r in rules if r.doc_id == 8} == {28_000 * 12}


def test_odd_tables_tokens(odd, tmp_path):
    ends = Counter((r.doc_id, r.doc_tokens) for r in packing.pack(odd, default_path()).where("start + length = doc_tokens").collect())
    assert sum(ends.values()) == odd.count() and ends[None, 1] == 1 and sum(n for (i, _), n in ends.items() if i == 7) == 3
    rows = token_shards.training_order(odd, default_path(), width=512, shard_slots=64)
    assert sum(len({p.start for p in r.pieces if p.start == 0}) > 0 for r in rows.collect()) > 0
    assert sum(p.length for r in rows.collect() for p in r.pieces) == sum(r.length for r in packing.pack(odd, default_path()).collect())


def test_odd_tables_models(odd, spark):
    rated = spark.createDataFrame([(7, 2), (8, 0), (9, 1), (9, 2)], "doc_id long, grade int")
    model = quality.train(odd, rated)
    assert quality.score(odd, model).count() == odd.count() and quality.keep_good(odd, model).columns == odd.columns
    scores = lm_score.score(odd, block_bytes=300_000).collect()
    assert len(scores) == odd.count() and all(r.score < 0 and r.base_score < 0 for r in scores) and sum(r.n_tokens == 1 for r in scores) == 3
    mixed = mixing.mix(odd)
    assert mixed.columns == odd.columns and mixed.count() <= odd.count()


def test_stages_keep_the_columns_of_documents(docs, empty, odd, spark):
    base = docs.drop("score")
    for name, stage in corpus_pipeline.STAGES[:4]:
        assert stage(spark, base, SF).schema == base.schema, name
        assert stage(spark, empty, SF).count() == 0, name
        assert stage(spark, odd, SF).columns == odd.columns, name
    assert corpus_pipeline.STAGES[4][1](spark, empty, SF).count() == 0


def test_pipeline_applies_its_stages_in_turn(spark):
    """Each stage's decisions, made again by hand on what the one before it kept."""
    given = spark.read.parquet(f"{SF}/documents.parquet")
    good = quality.score(given, quality.train(given, quality.labels_table(spark, SF))).where("kept").select("doc_id")
    kept = {"quality": given.join(good, "doc_id", "left_semi").select(*given.columns).persist()}
    kept["lines"] = line_dedup.dedup_lines(kept["quality"]).persist()
    rows = {r.doc_id: r.text for r in kept["lines"].collect()}
    sets = {i: {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} for i, t in rows.items() if (w := (t or "").encode().lower().split())}
    root = {i: i for i in sets}
    for i in sorted(sets):
        for j in sorted(sets):
            if j < i and root[i] != root[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = {k: a if v == b else v for k, v in root.items()}
    alone = {i for i in rows if root.get(i, i) == i}
    kept["near"] = kept["lines"].where(F.col("doc_id").isin(sorted(alone))).persist()
    last = {r.doc_id for r in mixing.mix(kept["near"]).collect()}
    out = corpus_pipeline.run(spark, SF).collect()
    assert {r.doc_id for r in out} == last and 0 < len(last) < len(alone) < given.count()
    encoded = {i: len(e) // 4 + 1 for i, e in zip(rows, WordBpe(default_path()).encode(list(rows.values())), strict=True)}
    sizes = Counter()
    for r in out:
        sizes[r.doc_id] += r.length
    assert sizes == Counter({i: encoded[i] for i in last})


def test_ratings_of_held_out_documents_are_predicted(spark):
    """A model fit on half of the rated documents orders the other half: good ones above the rest."""
    given = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rated = quality.labels_table(spark, "/root/testdata/sf0.01")
    half = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(2))
    model = quality.train(given, rated.where(half == 0))
    rows = quality.score(given, model).join(rated.where(half == 1), "doc_id").collect()
    good, bad = [r.score for r in rows if r.grade == 2], [r.score for r in rows if r.grade < 2]
    above = np.mean([g > b for g in good for b in bad])
    assert above > 0.85 and np.mean([(r.p_good >= 0.5) == (r.grade == 2) for r in rows]) > 0.8, above


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{SF}/documents.parquet'")
    got, want = registry.QUERIES[name](spark, SF), con.sql(registry.ORACLES[name])
    order = [want.columns.index(c) for c in got.columns]
    assert sorted(map(tuple, got.collect())) == sorted(tuple(r[i] for i in order) for r in want.fetchall())


def test_scores_are_the_same_whatever_documents_share_the_state(monkeypatch):
    """Short documents are many a block: their model states are held by groups, not all at once."""
    rng = np.random.default_rng(4)
    texts = [b" ".join(rng.choice([b"aa", b"bb", b"cc", b"dd", b"rare"], int(rng.integers(0, 60))).tolist()) for _ in range(50)]
    t = lm_score.Tokens(texts)
    _, inverse, n = np.unique(t.hash, return_inverse=True, return_counts=True)
    c = np.where(n[inverse] < n.max() / 3, 0, n[inverse])
    spelling = np.zeros((4, 1 << 19)), np.zeros((4, 1 << 19), np.uint8)
    score = lambda: lm_score.log_probabilities(t, [c, c // 3], np.full(50, 1000), np.full(50, 10), spelling)
    whole, held, make = score(), [], lm_score.Switch
    monkeypatch.setattr(lm_score, "GROUP", 8)
    monkeypatch.setattr(lm_score, "Switch", lambda docs, start: held.append(docs) or make(docs, start))
    assert np.array_equal(score(), whole) and max(held) == 8


def test_nodes_of_paths_are_counted_without_the_own_tokens():
    rng = np.random.default_rng(8)
    texts = [b" ".join(b"w%d" % i for i in rng.zipf(1.4, int(rng.integers(0, 80))).clip(0, 300)) for _ in range(30)]
    t, bits = lm_score.Tokens(texts), 30
    begins = lm_score.ruler(np.bincount((t.hash >> np.uint64(48)).astype(np.int64), minlength=1 << 16))
    code = lm_score.path_of(t.hash, begins).astype(np.int64)
    assert (np.diff(lm_score.path_of(np.sort(t.hash), begins).astype(np.int64)) >= 0).all() and code.max() < 1 << lm_score.DEPTH
    keys, found = t.path_keys(bits, begins), []
    for kind, levels in ((0, lm_score.DEPTH - lm_score.TOP), (1, lm_score.UPPER), (2, lm_score.LOWER)):
        ascending, place = keys[kind]
        at = lm_score.places_of(kind, ascending, bits, begins)
        rows = lm_score.paths(at, np.bincount(place, minlength=len(ascending)), levels, "<u4")
        found.append(lm_score.unpack_paths([lm_score.pack_paths(at[:5], rows[:5]), lm_score.pack_paths(at[5:], rows[5:])], [5, len(rows) - 5], at, levels))
        assert np.array_equal(found[-1], rows)
    own = np.arange(30) % 2
    top = np.bincount(code >> (lm_score.DEPTH - lm_score.TOP), minlength=1 << lm_score.TOP)
    got = lm_score.Nodes(t, [p for _, p in keys], begins, top, found, own).of(np.arange(len(t.hash)))
    before = t.back(t.hash, lm_score.START)
    for i in rng.integers(0, len(code), 40).tolist():
        others = (t.doc != t.doc[i]) | (own[t.doc[i]] == 0)
        same = [others & (code >> (lm_score.DEPTH - j) == code[i] >> (lm_score.DEPTH - j)) for j in range(lm_score.DEPTH + 1)]
        alone, after = [int(x.sum()) for x in same], [int((x & (before == before[i])).sum()) for x in same]
        assert got[0][i] == code[i] and [*got[1][i], got[2][i][-1]] == alone and [*got[3][i], got[4][i][-1]] == after


def test_shares_of_the_word_and_the_pair_are_mixed_in_the_logistic_domain():
    """At first a bit's probability is that of the weighted sum of what the counts predict, not a weighted mean of their shares."""
    whole, child, node, after = (np.array([[x]]) for x in (100, 20, 40, 30))
    for path in (np.array([0]), np.array([1 << (lm_score.DEPTH - 1)])):
        owner, bit, slot, gate, inputs = lm_score.decisions(path, whole, child, node, after)
        sign, q = (1 if path[0] else -1), (30 + lm_score.PRIOR * 0.2) / (40 + lm_score.PRIOR)
        assert owner.tolist() == [0] and bit.tolist() == [float(path[0] > 0)]
        assert np.allclose(inputs[:, 0], [sign * math.log(0.2 / 0.8), sign * math.log(q / (1 - q))])
        walk = lm_score.Walk(1)
        walk.predict(np.zeros(1, np.int64), slot, gate, inputs)
        assert np.allclose(walk.mixer.mixed, 1 / (1 + np.exp(-(0.3 * inputs[0] + 0.7 * inputs[1]))))
    assert not len(lm_score.decisions(path, whole, whole, node, after)[0])  # training leaves nothing open


def test_probabilities_of_all_words_sum_up_to_one():
    """Every known word as the second of a text, and the chance of an unknown one, which the switch has."""
    words = [b"w%d" % i for i in range(40)]
    count = {w: i % 7 + 1 for i, w in enumerate(words)} | {b"": 9}
    after = {w: i % 3 for i, w in enumerate(words)} | {b"": 2}
    of = {int(h): w for h, w in zip(lm_score.Tokens(words).hash[::2].tolist(), words, strict=True)} | {int(lm_score.END): b""}
    hashes = np.array(sorted(of), np.uint64)
    begins = lm_score.ruler(np.zeros(1 << 16))
    path = lm_score.path_of(hashes, begins)
    rows = [lm_score.paths(path, np.array([x[of[h]] for h in hashes.tolist()]), lm_score.DEPTH) for x in (count, after)]
    total = 0.0
    for i in range(len(hashes)):
        whole, pair = (x[i : i + 1] for x in rows)
        owner, bit, slot, gate, inputs = lm_score.decisions(path[i : i + 1].astype(np.int64), whole[:, :-1], whole[:, 1:], pair[:, :-1], pair[:, 1:])
        p = lm_score.Walk(1).predict(np.zeros(len(bit), np.int64), slot, gate, inputs)
        total += np.prod(np.where(bit > 0, p, 1 - p))
    assert abs(total - 1) < 1e-9


def test_sequences_travel_as_small_as_before():
    ids = np.random.default_rng(5).zipf(1.3, 2048).clip(0, 49_000).astype("<u2").tobytes()
    assert token_shards.restored(token_shards.squeezed(ids), 2048) == ids
    assert len(token_shards.squeezed(ids)) < 1.05 * len(zlib.compress(ids, 1))


def test_workers_give_free_memory_back():
    import os

    import psutil

    from rangegate.llm import near_dedup, text

    resident, used = lambda: psutil.Process(os.getpid()).memory_info().rss, []

    def run(key, table):
        held = [bytes(50_000) for _ in range(3000)]
        used.append((resident(), held.pop()))  # one piece above the free ones is still held
        return key, table

    assert text.frugal(run)(1, 2) == (1, 2) and resident() < used[0][0] - 75_000_000
    assert list(text.frugal(lambda given: iter(given))([3, 4])) == [3, 4] and text.frugal(lambda key, left, right: left + right)(0, 1, 2) == 3
    assert near_dedup.frugal is text.frugal
