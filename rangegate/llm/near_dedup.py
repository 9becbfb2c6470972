"""Near-duplicate join on word shingles with token-combination prefixes.

Two documents link when the Jaccard similarity of their sets of distinct five-word shingles is at least ``PERCENT`` / 100.
All links are found; what is pruned is proven not to be one.

* Documents with one shingle set form a node (64-bit hash of the set); only nodes are joined.
* Shingles have one global order, by the number of nodes that hold them and then by hash; up to ``frequent`` holders they
  are rare. Nodes are dealt to blocks by their hash, and ``blockcounts`` answers each block with the totals of its
  shingles, cut to the bits that tell them apart but for one in 2^``SPARE_BITS``; a total is the same wherever the
  shingle stands and never too low. A shingle of one node alone is never indexed.
* A linked pair shares a shingle within both prefixes of length n - ceil(t n) + 1. If a document's prefix holds rare
  shingles only, each is indexed alone. Otherwise the prefix is extended by k - 1, so that a pair shares k shingles in
  it: one rare shingle, indexed alone, or k frequent ones. The frequent shingles fall into k - 1 classes by hash, two of
  the k shared ones into the same class, so pairs of frequent shingles of one class are indexed. k follows bands of the
  set size whose bounds grow by 1/t; linked sizes lie in one band or in neighbours, and each document is indexed for its
  own band and the next.
* First the nodes of a key are compared with one of them; pairs that cannot reach t by size or by the number of shared
  keys are left out, the others verified on the whole sets, and components follow from these links. Then all pairs of
  one key in different components are compared, so that no link between components is lost. Keys of frequent shingles
  that have the same smallest node are merged for this, as variants of one text share hundreds of them, and a pair is met
  once a merged group and not once a key; parity maps of the sets rule most of these pairs out before they are formed.
  So a group of copies costs its size, not its square.

Defined results: null texts and texts without words have no shingles and stand alone; a text of fewer than five words is
one shingle; a repeated doc_id is one more document; rows with a null doc_id take part, and a class of nothing else has
a null id; an empty table gives an empty result; other columns are ignored. ``keep_one`` knows rows by their id and
the hash of their text: of a class the row with the smallest of both stays, and rows without an id go if one with an id is there.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangegate.llm.blockcounts import cut, key_bits, pack, pack_keys, slices, totals, unpack, unpack_keys
from rangegate.llm.graph import checkpoints, connected_components, release, stored
from rangegate.llm.text import Rolling, WordHasher, blocks_for, columns, distinct, documents, frugal, mix64, signed, text_bytes

SHINGLE_WORDS = 5
PERCENT = 75
BLOCK_BYTES = 8 << 20
SPARE_BITS = 8
PARITY_WORDS = 8
U64 = np.uint64


class Shingles:
    def __init__(self, width: int = SHINGLE_WORDS):
        self.width, self.hasher, self.rolling = width, WordHasher(fold=True), Rolling()

    def each(self, texts: list[bytes | None]) -> Iterator[np.ndarray]:
        """Sorted distinct 64-bit shingle hashes of each text."""
        for x in self.hasher.each(texts):
            yield distinct(self.rolling.windows(x, min(self.width, len(x)))) if len(x) else x


def node_of(shingles: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(shingles.tobytes()) - (1 << 63)


def share(n, percent: int):
    """Least overlap that a set of n shingles needs with any partner: ceil(percent n / 100)."""
    return -(-n * percent // 100)


def _features(docs: DataFrame) -> DataFrame:
    """doc_id, own (hash of the text), node, n of every row."""

    def run(batches: Iterator) -> Iterator:
        shingles = Shingles()
        for ids, own, texts in columns(batches, "doc_id", "own", "text"):
            found = [(node_of(s), len(s)) for s in shingles.each(texts)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(own, pa.int64()), pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int32())], ["doc_id", "own", "node", "n"])

    own = F.xxhash64("text").alias("own")
    return docs.select("doc_id", own, F.col("text").cast("binary").alias("text")).mapInArrow(frugal(run), "doc_id long, own long, node long, n int")


def _dealt(docs: DataFrame, blocks: int) -> DataFrame:
    """blk, node, text: texts by the block of their node; copies of a node go once a task."""

    def run(batches: Iterator) -> Iterator:
        shingles, seen = Shingles(), set()
        for _, texts in columns(batches, "doc_id", "text"):
            out = []
            for text, s in zip(texts, shingles.each(texts), strict=True):
                node = node_of(s)
                if len(s) > 1 and node not in seen:  # a set of one shingle is linked with equal sets only
                    seen.add(node)
                    out.append(((node + (1 << 63)) * blocks >> 64, node, text))
            blk, nodes, kept = zip(*out, strict=True) if out else ((),) * 3
            yield pa.RecordBatch.from_arrays([pa.array(blk, pa.int32()), pa.array(nodes, pa.int64()), pa.array(kept, pa.binary())], ["blk", "node", "text"])

    return text_bytes(docs).mapInArrow(frugal(run), "blk int, node long, text binary")


def _block_sets(table: pa.Table) -> tuple[np.ndarray, list[np.ndarray]]:
    """The distinct nodes of a block and their sets."""
    _, first = np.unique(table.column("node").to_numpy(), return_index=True)
    own = table.take(pa.array(first))
    return own.column("node").to_numpy(), list(Shingles().each(own.column("text").to_pylist()))


def _holders(dealt: DataFrame, parts: int, bits: int) -> DataFrame:
    """blk, part, counts: for the distinct shingles of each block, in their order, how many nodes hold them."""

    def asks(key, table):
        _, sets = _block_sets(table)
        distinct_, counts = np.unique(cut(np.concatenate(sets), bits), return_counts=True)
        rows = [(part, pack_keys(distinct_[a:b], bits), pack(counts[a:b].astype("<u4"))) for part, a, b in slices(distinct_, parts)]
        part, keys, n = zip(*rows, strict=True)
        return pa.table({"blk": pa.array([key[0].as_py()] * len(rows), pa.int32()), "part": pa.array(part, pa.int32()), "keys": pa.array(keys, pa.binary()), "n": pa.array(n, pa.binary())})

    def answers(key, table):
        _, _, found = totals([unpack_keys(x, bits) for x in table.column("keys").to_pylist()], [unpack(x, "<u4") for x in table.column("n").to_pylist()])
        return pa.table({"blk": table.column("blk"), "part": table.column("part"), "counts": pa.array([pack(np.minimum(x, 0xFFFFFFFF).astype("<u4")) for x in found], pa.binary())})

    sent = dealt.groupBy("blk").applyInArrow(frugal(asks), "blk int, part int, keys binary, n binary")
    return sent.groupBy("part").applyInArrow(frugal(answers), "blk int, part int, counts binary")


def size_bands(percent: int, top: int = 1 << 40) -> list[int]:
    """Lower bounds of bands of set sizes; sizes in a ratio of at most 100 / percent lie in one band or in neighbours."""
    bounds = [2]
    while bounds[-1] < top:
        bounds.append(max(bounds[-1] + 1, -(-bounds[-1] * 100 // percent)))
    return bounds


def index_keys(s: np.ndarray, holders: np.ndarray, frequent: int, bands: list[int], percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray, bool]:
    """Keys of single shingles and keys of shingle pairs under which the set ``s`` is indexed, and whether its prefix has rare shingles only.

    ``holders`` has the number of sets that hold each shingle; those of one set alone fill the prefix and give no key.
    """
    n = len(s)
    none = np.empty(0, U64)
    if n < 2:
        return none, none, True  # an equal set is the same node
    need = share(n, percent)
    prefix = n - need + 1
    order = np.lexsort((s, holders))
    s, holders = s[order], holders[order]
    rares = int(np.searchsorted(holders, frequent, side="right"))
    alone = int(np.searchsorted(holders, 1, side="right"))
    if rares >= prefix:
        return s[min(alone, prefix) : prefix], none, True
    common = s[rares:]
    own = int(np.searchsorted(bands, n, side="right")) - 1
    found = []
    for band in (own, own + 1):
        k = max(2, bands[band] // 8)
        held = common[: max(0, n - need + k - rares)]
        if len(held) < 2:
            continue
        group = mix64(held + U64(band)) % U64(k - 1)
        order = np.lexsort((held, group))
        held, group = held[order], group[order]
        step = 1
        while step < len(held) and (same := group[step:] == group[:-step]).any():
            with np.errstate(over="ignore"):
                found.append(mix64(held[:-step][same] * U64(3) + mix64(held[step:][same]) + U64(band)))
            step += 1
    return s[alone:rares], np.unique(np.concatenate(found)) if found else none, False


def _postings(dealt: DataFrame, holders: DataFrame, bits: int, frequent: int, percent: int) -> DataFrame:
    """key, paired (a key of two shingles), node, n, whole (the prefix of the node has rare shingles only)."""
    bands = size_bands(percent)

    def run(key, left, right):
        nodes, sets = _block_sets(left)
        replies = sorted(zip(right.column("part").to_pylist(), right.column("counts").to_pylist(), strict=True))
        counts = np.concatenate([unpack(x, "<u4") for _, x in replies])
        distinct_ = np.unique(cut(np.concatenate(sets), bits))
        keys, pairs, owners, sizes, whole = [np.empty(0, U64)], [], [], [], []
        for node, s in zip(nodes.tolist(), sets, strict=True):
            one, two, rare = index_keys(s, counts[np.searchsorted(distinct_, cut(s, bits))], frequent, bands, percent)
            m = len(one) + len(two)
            keys += [one, two]
            pairs.append(np.repeat([False, True], [len(one), len(two)]))
            owners.append(np.full(m, node, np.int64))
            sizes.append(np.full(m, len(s), np.int32))
            whole.append(np.full(m, rare, bool))
        return pa.table({"key": pa.array(signed(np.concatenate(keys)))} | {c: pa.array(np.concatenate(x)) for c, x in (("paired", pairs), ("node", owners), ("n", sizes), ("whole", whole))})

    return dealt.groupBy("blk").cogroup(holders.groupBy("blk")).applyInArrow(frugal(run), "key long, paired boolean, node long, n int, whole boolean")


def _shared_keys(postings: DataFrame) -> DataFrame:
    """Postings whose key has two nodes or more.

    A key of one shingle is held by as many nodes as its count allows, so a window serves; keys of pairs may be held by
    any number of nodes and go through a grouped minimum and a join, which can be split.
    """
    over = Window.partitionBy("key")
    single = postings.where("not paired").withColumn("lo", F.min("node").over(over)).withColumn("hi", F.max("node").over(over)).where("lo <> hi").drop("lo", "hi")
    paired = postings.where("paired")
    ends = paired.groupBy("key").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo <> hi").select("key")
    return single.unionByName(paired.join(ends, "key", "left_semi"))


def _bounded(pairs: DataFrame, percent: int) -> DataFrame:
    """Distinct (a, b) of rows (a, an, aw, b, bn, bw, paired) that sizes and shared keys leave possible.

    With single-shingle keys on both sides, the side whose prefix ends first cannot have any further common shingle in
    its prefix, so the overlap is at most the shared keys and the longer of the two remainders.
    """
    by_size = pairs.where(f"100 * least(an, bn) >= {percent} * greatest(an, bn)")
    counted = by_size.groupBy("a", "b").agg(F.sum(F.when(F.col("paired"), 0).otherwise(1)).alias("shared"), F.first("an").alias("an"), F.first("bn").alias("bn"), F.first("aw").alias("aw"), F.first("bw").alias("bw"))
    rest = lambda n: F.expr(f"ceil({n} * {percent} / 100) - 1")
    need = F.expr(f"{percent} * (cast(an as long) + bn)") / (100 + percent)
    return counted.where(~(F.col("aw") & F.col("bw")) | (F.col("shared") + F.greatest(rest("an"), rest("bn")) + 1e-6 >= need)).select("a", "b")


def _sets(docs: DataFrame, reps: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, s, bits: the sorted shingle hashes and the parity maps of the wanted nodes."""
    wanted = nodes.join(reps, "node").select("doc_id")

    def run(batches: Iterator) -> Iterator:
        shingles = Shingles()
        for _, texts in columns(batches, "doc_id", "text"):
            for at in range(0, len(texts), 1000):
                found = list(shingles.each(texts[at : at + 1000]))
                yield pa.RecordBatch.from_arrays([pa.array([node_of(s) for s in found], pa.int64()), pa.array([signed(s) for s in found], pa.list_(pa.int64())), pa.array([parity(s) for s in found], pa.list_(pa.int64()))], ["node", "s", "bits"])

    matched = docs.join(wanted, docs["doc_id"].eqNullSafe(wanted["doc_id"]), "left_semi")
    return text_bytes(matched).mapInArrow(frugal(run), "node long, s array<long>, bits array<long>").dropDuplicates(["node"])


def _overlaps(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """a, b, their overlap o on the whole sets, and whether they link."""
    a, b = sets.select(F.col("node").alias("a"), F.col("s").alias("sa")), sets.select(F.col("node").alias("b"), F.col("s").alias("sb"))
    both = pairs.join(a, "a").join(b, "b").withColumn("o", F.size(F.array_intersect("sa", "sb")))
    return both.select("a", "b", "o", F.expr(f"100 * o >= {percent} * (size(sa) + size(sb) - o)").alias("linked"))


def parity(s: np.ndarray) -> np.ndarray:
    """PARITY_WORDS longs: bit i tells whether an odd number of shingles hash to i.

    Two such maps differ in at most as many bits as the sets differ in shingles.
    """
    bits = np.bincount(((s >> U64(40)) % U64(64 * PARITY_WORDS)).astype(np.int64), minlength=64 * PARITY_WORDS) & 1
    return np.packbits(bits.astype(np.uint8)).view(np.int64)


def _sides(rows: DataFrame, a: str, b: str) -> DataFrame:
    """Rows (a, an, aw, b, bn, bw, paired) with a < b, of two structs (node, n, whole)."""
    swap = F.col(f"{a}.node") > F.col(f"{b}.node")
    x, y = F.when(swap, F.col(b)).otherwise(F.col(a)), F.when(swap, F.col(a)).otherwise(F.col(b))
    return rows.select(x.alias("x"), y.alias("y"), "paired").select(F.col("x.node").alias("a"), F.col("x.n").alias("an"), F.col("x.whole").alias("aw"), F.col("y.node").alias("b"), F.col("y.n").alias("bn"), F.col("y.whole").alias("bw"), "paired")


def _merged(paired: DataFrame) -> DataFrame:
    """Rows (key, node, ...) in which the keys with one smallest node have become one key, that node, with each node once.

    Nodes that share a key still share one. Where the merged group would cost more comparisons than its keys do, as with
    a node that shares a key each with many others, the keys stay.
    """
    least = paired.groupBy("key").agg(F.min("node").alias("least"), F.count("*").alias("c"))
    rows = paired.join(least.select("key", "least"), "key")
    members = rows.drop("key").distinct()
    cost = least.groupBy("least").agg(F.sum(F.col("c") * F.col("c")).alias("apart"))
    worth = members.groupBy("least").agg(F.count("*").alias("u")).join(cost, "least").select("least", (F.col("u") * F.col("u") <= F.col("apart")).alias("worth"))
    together = members.join(worth.where("worth"), "least", "left_semi").select(F.col("least").alias("key"), *[c for c in members.columns if c != "least"])
    return together.unionByName(rows.join(worth.where("not worth"), "least", "left_semi").drop("least"))


def near_duplicates(docs: DataFrame, percent: int = PERCENT, frequent: int = 8, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, own (hash of the text), first (the row that stands for its
    class; all rows of a class without ids do). A shingle with more than ``frequent`` holders is frequent."""
    checkpoints(docs.sparkSession)
    rows = stored(_features(docs))
    blocks = blocks_for(docs, block_bytes)
    dealt = _dealt(docs, blocks)
    bits = key_bits(blocks, block_bytes, SPARE_BITS)
    postings = stored(_postings(dealt, _holders(dealt, blocks, bits), bits, frequent, percent))
    release(docs.sparkSession)  # the exchange of texts and the slices
    keys = stored(_shared_keys(postings))
    reps = rows.groupBy("node").agg(F.min("doc_id").alias("doc_id"))
    ends = lambda p: p.select(F.col("a").alias("node")).unionByName(p.select(F.col("b").alias("node"))).distinct()

    draw = F.xxhash64("node", F.col("key").bitwiseAND(3))
    pivots = keys.groupBy("key").agg(F.min(F.struct(draw.alias("draw"), "node", "n", "whole")).alias("p"))
    star = keys.join(pivots, "key").where("node <> p.node").select(F.struct("node", "n", "whole").alias("own"), F.struct("p.node", "p.n", "p.whole").alias("other"), "paired")
    pairs = _bounded(_sides(star, "own", "other"), percent).checkpoint()
    sets = stored(_sets(docs, reps, ends(pairs).unionByName(keys.where("paired").select("node")).distinct()))
    done = _overlaps(pairs, sets, percent).checkpoint()
    release(docs.sparkSession)
    links = done.where("linked").select("a", "b")
    components = connected_components(links)

    labelled = keys.join(components, "node", "left").withColumn("component", F.coalesce("component", "node"))
    mixed = labelled.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("key")
    left = labelled.join(mixed, "key", "left_semi")
    side = lambda rows, x: rows.select("key", "paired", F.struct("node", "n", "whole").alias(x), F.col("component").alias(f"{x}_c"), *[F.col("bits").alias(f"{x}_bits")] * ("bits" in rows.columns))
    met = "own.node < other.node and own_c <> other_c and 100 * least(own.n, other.n) >= {0} * greatest(own.n, other.n)".format(percent)
    differ = " + ".join(f"bit_count(own_bits[{i}] ^ other_bits[{i}])" for i in range(PARITY_WORDS))
    near = f"{100 + percent} * ({differ}) <= {100 - percent} * (own.n + other.n)"
    one, two = left.where("not paired"), stored(_merged(stored(left.where("paired")))).join(sets.select("node", "bits"), "node")
    across = side(one, "own").join(side(one, "other").drop("paired"), "key").where(met).select("own", "other", "paired")
    across = across.unionByName(side(two, "own").join(side(two, "other").drop("paired"), "key").where(f"{met} and {near}").select("own", "other", "paired"))
    rest = _bounded(_sides(across, "own", "other"), percent).join(done, ["a", "b"], "left_anti").checkpoint()
    del across, one, two, left, mixed, labelled
    release(docs.sparkSession)
    if not rest.isEmpty():
        more = ends(rest).join(sets.select("node"), "node", "left_anti")
        found = _overlaps(rest, sets.unionByName(_sets(docs, reps, more)), percent).where("linked").select("a", "b").checkpoint()
        if not found.isEmpty():
            components = connected_components(links.unionByName(found))

    grouped = rows.where("n > 0").join(components, "node", "left").select("doc_id", "own", "n", F.coalesce("component", "node").alias("node"))
    least = grouped.groupBy("node").agg(F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "own"))).alias("first"))
    first = F.col("first").isNull() | F.struct("doc_id", "own").eqNullSafe(F.col("first"))
    out = grouped.join(least, "node").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.col("first.doc_id").alias("component_id"), "own", first.alias("first"))
    return out.unionByName(rows.where("n = 0").select("doc_id", F.lit(0).cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id"), "own", F.lit(True).alias("first")))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with one row of each class of near duplicates, the first by id and hash of the text."""
    gone = near_duplicates(docs, **options).where("not first").select(F.col("doc_id").alias("gone__"), F.col("own").alias("own__"))
    return docs.join(gone, docs["doc_id"].eqNullSafe(gone["gone__"]) & (F.xxhash64(docs["text"]) == gone["own__"]), "left_anti")


def op5_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir)).select("doc_id", "n_shingles", "component_id")
