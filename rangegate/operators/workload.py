"""Key sets and query sets on the given tables, from integer arithmetic only, so that DuckDB can make them again."""

from __future__ import annotations

from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangegate.functions.hashes import P, mix, mix_numpy, wide
from rangegate.functions.keys import KeySpace, cents, composite, timestamp_code

ORIGIN = 1704067200000000  # 2024-01-01 in microseconds


@dataclass(frozen=True)
class KeySet:
    """Bits of a code; widths of long and short queries and the reach of correlated ones, by the free bits of the set."""

    name: str
    bits: int
    long: int
    short: int
    reach: int

    @property
    def space(self) -> KeySpace:
        return KeySpace(self.bits)


SETS = {s.name: s for s in (KeySet("ts", 42, 21, 7, 9), KeySet("user_ts", 53, 30, 10, 13), KeySet("val", 34, 15, 5, 6), KeySet("line", 21, 3, 2, 2), KeySet("price", 26, 9, 3, 4), KeySet("u62", 62, 35, 11, 15), KeySet("n62", 62, 35, 11, 15))}
GENERATED = 40_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def keys(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Distinct codes of a key set: run_id (one run), code."""
    if name == "ts":
        out = table(spark, sf_dir, "events").select(timestamp_code("ts", ORIGIN).alias("code"))
    elif name == "user_ts":
        out = table(spark, sf_dir, "events").select(composite(("user_id", 11), (timestamp_code("ts", ORIGIN), 42)).alias("code"))
    elif name == "val":
        out = table(spark, sf_dir, "events").select(composite((cents("value"), 17), ("event_id", 17)).alias("code"))
    elif name == "line":
        out = table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("code"))
    elif name == "price":
        out = table(spark, sf_dir, "lineitem").select(cents("l_extendedprice").alias("code"))
    else:
        out = generated(spark, name)
    return out.where("code is not null").distinct().select(F.lit(0).cast("long").alias("run_id"), "code")


def fitted(key_rows: DataFrame, ks: KeySet) -> KeySet:
    """The key set with as many bits as its largest code needs: tables that outgrow the declared ones lose no key."""
    top = key_rows.agg(F.max("code")).first()[0]
    return replace(ks, bits=max(ks.bits, int(top or 0).bit_length()))


def generated(spark: SparkSession, name: str, n: int = GENERATED, ids: DataFrame | None = None) -> DataFrame:
    """code: n keys, or one of each row of ``ids(id)``, of 62 bits, uniform (``u62``) or normal around the middle (``n62``); on Arrow batches, as the sums of
    a dozen hashes are too long an expression to be compiled.
    """

    def run(batches):
        for batch in batches:
            x = batch.column("id").to_numpy()
            if name == "u62":
                code = (mix_numpy(5, x) << 31) | mix_numpy(6, x)
            else:
                code = (1 << 61) + (sum(mix_numpy(10 + i, x) for i in range(12)) - 6 * P) * 21474836 + mix_numpy(30, x) % 21474836
            yield pa.RecordBatch.from_arrays([pa.array(code, pa.int64())], ["code"])

    return (spark.range(n) if ids is None else ids).mapInArrow(run, "code long")


def customer_codes(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Distinct codes of 62 bits hashed from the customers' keys: run_id (one run), code."""
    ids = table(spark, sf_dir, "customer").where("c_custkey is not null").select(F.col("c_custkey").alias("id"))
    return generated(spark, name, ids=ids).distinct().select(F.lit(0).cast("long").alias("run_id"), "code")


def event_queries(spark: SparkSession, sf_dir: str, ks: KeySet, every: int) -> DataFrame:
    """qid, lo, hi: ranges that begin at the time of each event whose id is divisible by ``every``."""
    top = F.lit((1 << ks.bits) - 1)
    rows = table(spark, sf_dir, "events").where(f"event_id % {every} = 0 and ts is not null")
    rows = rows.select(F.col("event_id").alias("qid"), F.least(timestamp_code("ts", ORIGIN), top).alias("lo"))
    return rows.select("qid", "lo", F.least(F.col("lo") + mix(44, F.col("qid")) % F.lit((1 << ks.long) - 1) + 2, top).alias("hi"))


def uniform_queries(spark: SparkSession, ks: KeySet, n: int, bits: int | None = None) -> DataFrame:
    """qid, lo, hi: left bounds anywhere, widths of 2 to 2^bits."""
    r = 1 << (ks.long if bits is None else bits)
    q = F.col("id")
    out = spark.range(n).select(q.alias("qid"), (wide(40, 41, q) % F.lit((1 << ks.bits) - r)).alias("lo"), (wide(42, 43, q) % F.lit(max(1, r - 1)) + 2).alias("w"))
    return out.select("qid", "lo", (F.col("lo") + F.col("w")).alias("hi"))


def correlated_queries(key_rows: DataFrame, ks: KeySet, n: int, bits: int | None = None) -> DataFrame:
    """qid, lo, hi: left bounds just above a key; the keys are the ``n`` with the smallest hash, a bounded sample."""
    r = 1 << (ks.short if bits is None else bits)
    first = key_rows.select("code").distinct().orderBy(mix(45, F.col("code")), "code").limit(n)
    ranked = first.select("code", (F.row_number().over(Window.orderBy(mix(45, F.col("code")), "code")) - 1).cast("long").alias("qid"))
    top = F.lit((1 << ks.bits) - 1)
    lo = F.least(F.col("code") + 1 + mix(46, F.col("qid")) % F.lit(1 << ks.reach), top)
    return ranked.select("qid", lo.alias("lo"), (mix(44, F.col("qid")) % F.lit(max(1, r - 1)) + 2).alias("w")).select("qid", "lo", F.least(F.col("lo") + F.col("w"), top).alias("hi"))


def split_queries(spark: SparkSession, key_rows: DataFrame, ks: KeySet, n: int) -> DataFrame:
    """Even qids are long uniform queries, odd ones short correlated queries."""
    return uniform_queries(spark, ks, n).where("qid % 2 = 0").unionByName(correlated_queries(key_rows, ks, n).where("qid % 2 = 1"))


def point_queries(spark: SparkSession, ks: KeySet, n: int) -> DataFrame:
    return uniform_queries(spark, ks, n).select("qid", "lo", F.col("lo").alias("hi"))


def mixed_queries(spark: SparkSession, ks: KeySet, n: int) -> DataFrame:
    """Half points, half ranges."""
    return uniform_queries(spark, ks, n).select("qid", "lo", F.when(F.col("qid") % 2 == 0, F.col("lo")).otherwise(F.col("hi")).alias("hi"))


def real_split(key_rows: DataFrame, ks: KeySet) -> tuple[DataFrame, DataFrame]:
    """Keys and, from one key in eleven taken out of them, left bounds of short queries."""
    bound = mix(47, F.col("code")) % 11 == 0
    lo = F.col("code")
    bounds = key_rows.where(bound).select(lo.alias("qid"), lo.alias("lo"), F.least(lo + 2 + mix(44, lo) % F.lit(max(1, (1 << ks.short) - 1)), F.lit((1 << ks.bits) - 1)).alias("hi"))
    return key_rows.where(~bound), bounds


def present_queries(key_rows: DataFrame, n: int) -> DataFrame:
    """Points at existing keys, which no filter may reject."""
    return key_rows.select("code").distinct().orderBy(mix(48, F.col("code")), "code").limit(n).select(F.col("code").alias("qid"), F.col("code").alias("lo"), F.col("code").alias("hi"))
