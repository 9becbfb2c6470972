"""Mixing of sources to target weights: raking to marginals, then sampling by calibrated probabilities.

Documents fall into cells of source, language and topic. Iterative proportional fitting scales the cells' inclusion
probabilities until the expected tokens meet the target of every source, language and topic; probabilities stay at most
1. A document is kept when a uniform number from its id lies below its cell's probability, whatever the partitions.

Targets are tokens per category; where none are given, a category's share is its share of the corpus to the power
``alpha``, of a total of ``fraction`` of all tokens. Topics are those of ``topic_of`` unless another
function of the text's bytes is given.

Defined results: null categories form the category ''; null texts have no tokens, so their cell decides; a null doc_id
draws by its text; equal ids draw alike; a category without target weight is left out; an empty table gives an empty
result; other columns are kept, whatever their names but for those ending in two underscores that are named below. Up to
``max_cells`` cells the fit runs on the driver, beyond that on tables; both take the same ``rounds`` and give the same
probabilities.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangegate.llm.graph import checkpoints
from rangegate.llm.text import documents

DIMENSIONS = ("source", "lang", "topic")
ALPHA = 0.8
FRACTION = 0.6
MAX_CELLS = 100_000
ROUNDS = 50


def topic_of(text: bytes) -> str:
    """Topic by plain marks of the text (ours): tables, mark-up or noise, legal, data, else prose by length."""
    n = len(text)
    rest = lambda marks: n - len(text.translate(None, marks))
    if text.count(b"|") * 50 > n:
        return "table"
    if rest(b"#*$%&<>") * 50 > n:
        return "marked"
    if b"licen" in text.lower():
        return "legal"
    if rest(b"0123456789") * 50 > n:
        return "data"
    return "short prose" if n < 500 else "prose" if n < 5000 else "long prose"


def measure(topic: Callable[[bytes], str]):
    @F.pandas_udf("n long, topic string")
    def measured(text: pd.Series) -> pd.DataFrame:
        texts = [t or b"" for t in text]
        return pd.DataFrame({"n": [len(t.split()) for t in texts], "topic": [topic(t) for t in texts]})

    return measured


def with_cells(docs: DataFrame, topic: Callable[[bytes], str] = topic_of) -> DataFrame:
    """``docs`` with n_tokens__ (words), topic__ and the categories, named with two underscores."""
    marked = docs.withColumn("m__", measure(topic)(F.col("text").cast("binary")))
    own = {"n_tokens__": F.col("m__.n"), "topic__": F.coalesce("m__.topic", F.lit(""))}
    return marked.withColumns(own | {f"{c}__": F.coalesce(F.col(c).cast("string"), F.lit("")) if c in docs.columns else F.lit("") for c in ("source", "lang")}).drop("m__")


def default_targets(totals: dict[str, float], alpha: float, budget: float) -> dict[str, float]:
    shares = {k: v**alpha for k, v in totals.items() if v > 0}
    whole = sum(shares.values())
    return {k: budget * v / whole for k, v in shares.items()}


def rake(tokens: np.ndarray, codes: list[np.ndarray], targets: list[np.ndarray], start: float, rounds: int = ROUNDS) -> np.ndarray:
    """Inclusion probability of each cell by proportional fitting with a ceiling of 1."""
    p = np.full(len(tokens), start)
    for _ in range(rounds):
        for code, target in zip(codes, targets, strict=True):
            have = np.bincount(code, p * tokens, minlength=len(target))
            factor = np.divide(target, have, out=np.where(target > 0, 1.0, 0.0), where=have > 0)
            p = np.minimum(1.0, p * factor[code])
    return p


def _rake_tables(cells: DataFrame, targets: dict[str, dict[str, float]] | None, alpha: float, fraction: float, rounds: int) -> DataFrame:
    """The same fit over tables of cells and of categories, for any number of them; every tenth round is cut off by a checkpoint."""
    spark, p = cells.sparkSession, cells.withColumn("p__", F.lit(fraction))
    for c in DIMENSIONS:
        if (targets or {}).get(c):
            own = spark.createDataFrame(list(targets[c].items()), f"{c}__ string, t_{c} double")
        else:
            have = cells.groupBy(f"{c}__").agg(F.sum("tokens").alias("h")).where("h > 0")
            whole = have.agg(F.sum(F.pow("h", F.lit(alpha))).alias("w"), F.sum("h").alias("all"))
            own = have.join(F.broadcast(whole)).select(f"{c}__", (F.pow("h", F.lit(alpha)) / F.col("w") * F.col("all") * fraction).alias(f"t_{c}"))
        p = p.join(own, f"{c}__", "left").fillna(0.0, [f"t_{c}"])
    for i in range(rounds):
        for c in DIMENSIONS:
            have = p.groupBy(f"{c}__").agg(F.sum(F.col("p__") * F.col("tokens")).alias("h"))
            factor = F.when(F.col("h") > 0, F.col(f"t_{c}") / F.col("h")).otherwise(F.when(F.col(f"t_{c}") > 0, 1.0).otherwise(0.0))
            p = p.join(have, f"{c}__").withColumn("p__", F.least(F.lit(1.0), F.col("p__") * factor)).drop("h")
        p = p.checkpoint()
    return p


def cell_probabilities(marked: DataFrame, targets: dict[str, dict[str, float]] | None = None, alpha: float = ALPHA, fraction: float = FRACTION, max_cells: int = MAX_CELLS, rounds: int = ROUNDS) -> DataFrame:
    """source__, lang__, topic__, p__; from the cells of all of ``marked``. Written first, so every use sees one fit."""
    spark = marked.sparkSession
    checkpoints(spark)
    keys = [f"{c}__" for c in DIMENSIONS]
    cells = marked.groupBy(*keys).agg(F.sum("n_tokens__").cast("double").alias("tokens")).checkpoint()
    if cells.count() > max_cells:
        return _rake_tables(cells, targets, alpha, fraction, rounds).select(*keys, "p__")
    rows = sorted(cells.collect(), key=lambda r: tuple(r)[:3])
    totals: list[dict[str, float]] = [{} for _ in keys]
    for r in rows:
        for d, held in enumerate(totals):
            held[r[d]] = held.get(r[d], 0.0) + r[3]
    budget = fraction * sum(totals[0].values())
    wanted = [dict((targets or {}).get(c) or default_targets(t, alpha, budget)) for c, t in zip(DIMENSIONS, totals, strict=True)]
    codes, aims = [], []
    for d, (held, aim) in enumerate(zip(totals, wanted, strict=True)):
        number = {name: i for i, name in enumerate(held)}
        codes.append(np.array([number[r[d]] for r in rows], np.int64))
        aims.append(np.array([aim.get(name, 0.0) for name in held]))
    p = rake(np.array([r[3] for r in rows]), codes, aims, fraction, rounds)
    return F.broadcast(spark.createDataFrame([(*tuple(r)[:3], float(x)) for r, x in zip(rows, p, strict=True)], "source__ string, lang__ string, topic__ string, p__ double"))


def with_probability(docs: DataFrame, seed: int = 7, **options) -> DataFrame:
    """``docs`` with the cell columns, p__, and kept__."""
    marked = with_cells(docs)
    cells = cell_probabilities(marked, **options)
    draw = F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("t"), F.coalesce("text", F.lit("")))), F.lit(seed))
    uniform = F.shiftrightunsigned(draw, 11).cast("double") / F.lit(float(1 << 53))
    return marked.join(cells, [f"{c}__" for c in DIMENSIONS]).withColumn("kept__", uniform < F.col("p__"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The sampled documents with the columns of ``docs``."""
    return with_probability(docs, **options).where("kept__").select(*docs.columns)


def op7_raked_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = with_probability(documents(spark, sf_dir))
    return out.select("doc_id", F.col("source__").alias("source"), F.col("lang__").alias("lang"), F.col("topic__").alias("topic"), F.col("n_tokens__").alias("n_tokens"), F.col("p__").alias("probability"), F.col("kept__").alias("kept"))
