"""Quality classifier: ordinal cumulative-link regression on graded ratings over hashed text.

Ratings have the ordered grades 0 (toxic), 1 (poor) and 2 (good). One weight vector over hashed features and two ordered
thresholds give P(grade >= g) = sigmoid(score - threshold_g), hence the expected grade and the tail probability
P(grade >= 2) by which documents are selected.

Features are the distinct words of the whole text without the marks around them, A-Z-folded, their beginnings of 4 to 8
bytes, the shapes of its words (letters and digits by class, runs once) with the tenth of all words that has the shape,
and the tenths of distinct words and of words with marks that prose lacks; each is hashed to a slot. Slots whose rate does not differ between grades by ``min_z`` standard errors stay 0.

The fit uses a bounded sample of rated documents: the ``max_rated`` with the smallest hash of doc_id. Defined results: a
null or empty text has no features and gets the score 0; documents without rating are scored like others; a document
rated twice counts with its lowest grade; ratings with a null id or null values are left out; without ratings of two
grades nothing is rejected; a null doc_id is scored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.llm.text import columns, documents, frugal, text_bytes

SLOTS = 1 << 18
GRADES = 3
MAX_RATED = 6_000
MIN_TAIL = 0.5
_MARKS = bytes(range(0x21, 0x30)) + bytes(range(0x3A, 0x41)) + bytes(range(0x5B, 0x61)) + bytes(range(0x7B, 0x7F))
_CLASSES = bytes(0x61 if 0x61 <= c <= 0x7A or c >= 0x80 else 0x41 if 0x41 <= c <= 0x5A else 0x30 if 0x30 <= c <= 0x39 else c for c in range(256))
_PROSE = b"aA0.,;:'\"()-?"
_RUNS = re.compile(rb"(.)\1+", re.DOTALL)


class Features:
    """Sorted distinct feature slots of a text; words and shapes are kept per worker up to ``limit``."""

    def __init__(self, slots: int = SLOTS, limit: int = 120_000):
        self.slots, self.limit = slots, limit
        self.known: dict[bytes, tuple[tuple[int, ...], bytes]] = {}
        self.shapes: dict[bytes, bytes] = {}

    def _slot(self, feature: bytes) -> int:
        return xxhash.xxh3_64_intdigest(feature) % self.slots

    def _word(self, word: bytes) -> tuple[tuple[int, ...], bytes]:
        if len(self.known) >= self.limit:
            self.known.clear()
            self.shapes.clear()
        bare = word.strip(_MARKS).lower()
        slots = (self._slot(b"w" + bare), *(self._slot(b"b" + bare[:n]) for n in range(4, 9) if n < len(bare)))
        shape = _RUNS.sub(rb"\1", word.translate(_CLASSES))
        value = self.known[word] = (slots, self.shapes.setdefault(shape, shape))
        return value

    def of(self, text: bytes | None) -> np.ndarray:
        words = Counter((text or b"").split())
        total, shapes, slots, known = sum(words.values()), Counter(), set(), self.known
        for word, n in words.items():
            own, shape = known.get(word) or self._word(word)
            slots.update(own)
            shapes[shape] += n
        marked = sum(n for shape, n in shapes.items() if shape.translate(None, _PROSE))
        for shape, n in shapes.items():
            if 10 * n >= total:
                slots.add(self._slot(b"s%d " % (10 * n // total) + shape))
        if total:
            slots.update((self._slot(b"d%d" % (10 * len(words) // total)), self._slot(b"m%d" % (10 * marked // total))))
        return np.array(sorted(slots), np.int32)


@dataclass
class OrdinalModel:
    weights: np.ndarray
    thresholds: np.ndarray
    trained: bool

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade >= 1), P(grade >= 2), ... as columns."""
        return 1 / (1 + np.exp(-np.clip(score[:, None] - self.thresholds[None, :], -60, 60)))

    def scores(self, docs: list[np.ndarray]) -> np.ndarray:
        lengths = np.array([len(d) for d in docs], np.int64)
        if not lengths.sum():
            return np.zeros(len(docs))
        total = np.r_[0.0, np.cumsum(self.weights[np.concatenate(docs)], dtype=np.float64)]
        ends = np.cumsum(lengths)
        return total[ends] - total[ends - lengths]


def fit(docs: list[np.ndarray], grades: np.ndarray, slots: int = SLOTS, rounds: int = 120, rate: float = 0.1, penalty: float = 1e-3, min_z: float = 4.5, balance: float = 0.0) -> OrdinalModel:
    """Adam on the mean cumulative-link loss, a grade weighted by its rarity to the power ``balance``; slots below ``min_z`` stay 0."""
    present = np.unique(grades)
    if len(present) < 2:
        return OrdinalModel(np.zeros(slots, np.float32), np.arange(1 - GRADES / 2, GRADES / 2)[: GRADES - 1], False)
    by_grade = np.zeros((GRADES, slots), np.int32)
    for d, g in zip(docs, grades, strict=True):
        by_grade[g, d] += 1
    used, rate_all = np.zeros(slots, bool), by_grade.sum(axis=0) / len(docs)
    for g in present[1:]:
        n = int((grades >= g).sum())
        error = np.sqrt(np.maximum(rate_all * (1 - rate_all), 1e-12) * (1 / n + 1 / (len(docs) - n)))
        used |= np.abs(by_grade[g:].sum(axis=0) / n - by_grade[:g].sum(axis=0) / (len(docs) - n)) >= min_z * error
    docs = [d[used[d]] for d in docs]
    flat, row = np.concatenate(docs), np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    share = np.bincount(grades, minlength=GRADES)
    weight = (len(docs) / share[grades]) ** balance
    weight /= weight.sum()
    w, first, gap = np.zeros(slots), np.array([-1.0]), np.zeros(GRADES - 2)
    moments: dict[str, list] = {}

    def step(name: str, x: np.ndarray, g: np.ndarray, t: int) -> np.ndarray:
        m, v = moments.setdefault(name, [np.zeros_like(x), np.zeros_like(x)])
        m[:] = 0.9 * m + 0.1 * g
        v[:] = 0.99 * v + 0.01 * g * g
        return x - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9)

    for t in range(1, rounds + 1):
        thresholds = np.cumsum(np.r_[first, np.exp(gap)])
        score = np.bincount(row, w[flat], minlength=len(docs))
        # P(grade = g) is the difference of two sigmoids; the ends are 1 and 0
        tail = 1 / (1 + np.exp(-np.clip(score[:, None] - thresholds, -60, 60)))
        edge = np.c_[np.ones(len(docs)), tail, np.zeros(len(docs))]
        slope = edge * (1 - edge)
        at = np.arange(len(docs))
        p = np.maximum(edge[at, grades] - edge[at, grades + 1], 1e-12)
        up, down = weight * slope[at, grades] / p, weight * slope[at, grades + 1] / p
        d_score = down - up
        d_threshold = np.array([up[grades == g + 1].sum() - down[grades == g].sum() for g in range(GRADES - 1)])
        g_w = np.bincount(flat, d_score[row], minlength=slots) + penalty * w
        g_gap = np.array([d_threshold[i + 1 :].sum() * np.exp(gap[i]) for i in range(GRADES - 2)])
        w, first, gap = step("w", w, g_w, t), step("first", first, np.array([d_threshold.sum()]), t), step("gap", gap, g_gap, t)
    return OrdinalModel(w.astype(np.float32), np.cumsum(np.r_[first, np.exp(gap)]), True)


def graded(labels: DataFrame) -> DataFrame:
    """doc_id, grade from the quality and toxic ratings."""
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).otherwise(2)
    return labels.where("doc_id is not null and quality is not null and toxic is not null").groupBy("doc_id").agg(F.min(grade).cast("int").alias("grade"))


def train(docs: DataFrame, ratings: DataFrame, max_rated: int = MAX_RATED) -> OrdinalModel:
    """``ratings(doc_id, grade)``; the sample is bounded, so it may be broadcast to the scan and its features collected."""
    sample = ratings.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rated)

    def run(batches: Iterator) -> Iterator:
        features = Features()
        for ids, texts, grades in columns(batches, "doc_id", "text", "grade"):
            found = [features.of(t) for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(grades, pa.int32()), pa.array(found, pa.list_(pa.int32()))], ["doc_id", "grade", "slots"])

    rows = text_bytes(docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id"), "grade").mapInArrow(run, "doc_id long, grade int, slots array<int>")
    table = rows.dropDuplicates(["doc_id"]).toArrow().sort_by("doc_id").combine_chunks()
    slots = table.column("slots").combine_chunks()
    flat, ends = slots.flatten().to_numpy(), slots.offsets.to_numpy() if len(slots) else np.zeros(1, np.int32)
    return fit([flat[a:b] for a, b in zip(ends[:-1] - ends[0], ends[1:] - ends[0], strict=True)], table.column("grade").to_numpy().astype(np.int64))


def score(docs: DataFrame, model: OrdinalModel, min_tail: float = MIN_TAIL) -> DataFrame:
    """doc_id, score, expected_grade, p_good, kept of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator) -> Iterator:
        features, m = Features(), shared.value
        for ids, texts in columns(batches, "doc_id", "text"):
            s = m.scores([features.of(t) for t in texts])
            tails = m.tails(s)
            kept = tails[:, -1] >= min_tail if m.trained else np.ones(len(s), bool)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *(pa.array(x) for x in (s, tails.sum(axis=1), tails[:, -1], kept))], ["doc_id", "score", "expected_grade", "p_good", "kept"])

    return text_bytes(docs).mapInArrow(run, "doc_id long, score double, expected_grade double, p_good double, kept boolean")


def keep_good(docs: DataFrame, model: OrdinalModel, min_tail: float = MIN_TAIL) -> DataFrame:
    """The rows of ``docs`` that the model keeps, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator) -> Iterator:
        features, m = Features(), shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                texts = part.column("text").cast(pa.binary()).to_pylist()
                kept = m.tails(m.scores([features.of(t) for t in texts]))[:, -1] >= min_tail if m.trained else np.ones(len(texts), bool)
                yield part.filter(pa.array(kept))

    return docs.mapInArrow(frugal(run), docs.schema)


def labels_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graded(spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op3_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return score(docs, train(docs, labels_table(spark, sf_dir)))
