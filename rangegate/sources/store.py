"""Store of key runs: a partitioned Parquet table with a catalog, filters, filtered lookups and scans, and compaction."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from rangegate.functions.keys import KeySpace

CATALOG = "run_id long, level int, min_code long, max_code long, n_keys long, born_batch long"
#: Codecs by level: the few runs of the upper levels are plain, the bulk below is packed harder.
CODECS = {0: "none", 1: "none", 2: "lz4", 3: "zstd"}
LEVEL_STRIDE = 1 << 40


def shared_folder(spark: SparkSession) -> str:
    """A folder that all executors share: that of ``spark.checkpoint.dir``, or on a local master a new one of this machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if folder is None:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        import tempfile

        folder = tempfile.mkdtemp(prefix="runs-")
        spark.sparkContext.setCheckpointDir(folder)
    return f"{folder}/store-{uuid.uuid4().hex}"


def cut_runs(rows: DataFrame, space: KeySpace, run_bits: int, level: int = 0) -> DataFrame:
    """Rows with run_id: ranges of equal width by the leading bits of ``code``; run ids of levels do not meet."""
    return rows.withColumn("run_id", space.prefix("code", run_bits) + F.lit(level << 40)).withColumn("level", F.lit(level))


def balanced_runs(rows: DataFrame, run_rows: int, level: int = 0) -> DataFrame:
    """Rows with run_id and level: ranges of about ``run_rows`` rows, by approximate quantiles of the codes.

    The bounds of the runs are one number a run; rows find theirs by binary search over them.
    """
    base = level * LEVEL_STRIDE
    n = rows.count()
    runs = max(1, -(-n // run_rows))
    if runs == 1:
        return rows.withColumn("run_id", F.lit(base).cast("long")).withColumn("level", F.lit(level))
    cuts = sorted(set(rows.select(F.percentile_approx("code", [i / runs for i in range(1, runs)], 100_000).alias("c")).first().c))
    if len(cuts) <= 64:
        number = sum((F.when(F.col("code") >= c, 1).otherwise(0) for c in cuts), F.lit(0))
    else:
        shared = rows.sparkSession.sparkContext.broadcast(np.array(cuts))

        @F.pandas_udf("long")
        def place(code):
            return type(code)(np.searchsorted(shared.value, code.to_numpy(), side="right"))

        number = place("code")
    return rows.withColumn("run_id", number.cast("long") + F.lit(base)).withColumn("level", F.lit(level))


def catalog(rows: DataFrame, batch: int = 0) -> DataFrame:
    """One row per run: level, code range, number of keys."""
    level = F.first("level") if "level" in rows.columns else F.lit(0)
    return rows.groupBy("run_id").agg(level.alias("level"), F.min("code").alias("min_code"), F.max("code").alias("max_code"), F.count("*").alias("n_keys"), F.lit(batch).cast("long").alias("born_batch"))


def write_store(rows: DataFrame, path: str, codec: str | None = None, mode: str = "overwrite") -> None:
    """Sorted rows of each run in one folder of its own, so that lookups read surviving runs only; one codec for all its levels."""
    writer = rows.repartition("run_id").sortWithinPartitions("run_id", "code").write.partitionBy("level", "run_id")
    (writer.option("compression", codec) if codec else writer).parquet(path, mode=mode)


def write_levels(rows: DataFrame, path: str, levels: list[int]) -> None:
    """Each level with its codec into one store."""
    for i, level in enumerate(levels):
        write_store(rows.where(F.col("level") == level), path, CODECS.get(level, "zstd"), "overwrite" if i == 0 else "append")


def read_store(spark: SparkSession, path: str) -> DataFrame:
    """All rows of a store; run ids are longs, whatever type their folders' names suggest."""
    found = spark.read.parquet(path).schema
    kinds = {"run_id": LongType(), "level": IntegerType()}
    return spark.read.schema(StructType([StructField(f.name, kinds.get(f.name, f.dataType)) for f in found.fields])).parquet(path)


def read_runs(spark: SparkSession, path: str, run_ids: DataFrame) -> DataFrame:
    """The rows of some runs: the join prunes the other folders before they are read (dynamic partition pruning)."""
    wanted = run_ids.select(F.col("run_id").alias("wanted__")).where("wanted__ >= 0").distinct()  # a filter on this side makes it prune
    return read_store(spark, path).join(F.broadcast(wanted), F.col("run_id") == F.col("wanted__")).drop("wanted__")  # one number a run


def file_bytes(spark: SparkSession, path: str) -> DataFrame:
    """run_id, bytes: size of the files of each run, from file metadata; no data is read."""
    files = read_store(spark, path).select("run_id", F.col("_metadata.file_path").alias("f"), F.col("_metadata.file_size").alias("s"))
    return files.groupBy("run_id", "f").agg(F.max("s").alias("s")).groupBy("run_id").agg(F.sum("s").alias("bytes"))


def overlapping(cat: DataFrame, queries: DataFrame, space: KeySpace, bin_bits: int = 8) -> DataFrame:
    """run_id, qid, lo, hi of runs whose code range meets a query: an equi-join on coarse bins, then the exact test."""
    bins = lambda a, b: F.explode(F.sequence(space.prefix(a, bin_bits), space.prefix(b, bin_bits)))
    runs = cat.select("run_id", "min_code", "max_code").withColumn("bin", bins("min_code", "max_code"))
    asked = queries.select("qid", "lo", "hi").withColumn("bin", bins("lo", "hi"))
    first = F.col("bin") == space.prefix(F.greatest("lo", "min_code"), bin_bits)  # each pair in one bin only
    return asked.join(runs, "bin").where((F.col("min_code") <= F.col("hi")) & (F.col("max_code") >= F.col("lo")) & first).select("run_id", "qid", "lo", "hi")


def survivors(overlap: DataFrame, answers: DataFrame | None) -> DataFrame:
    """The overlapping runs without those whose filter proves a query empty; a run without an answer survives."""
    return overlap if answers is None else overlap.join(answers.where("not maybe").select("run_id", "qid"), ["run_id", "qid"], "left_anti")


def renamed(df: DataFrame, *names: str) -> DataFrame:
    """The named columns as new ones, so that two sides of a co-group may come from one table."""
    return df.select(*[F.col(c).alias(c) for c in names])


def closed_seek(rows: DataFrame, asked: DataFrame) -> DataFrame:
    """qid, first_key: least code at or above lo over the surviving runs, if it is within hi.

    Keys and queries of a run meet by binary search, so the work is the sum of both, not their product.
    """

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        codes, lo, hi = np.sort(left.column("code").to_numpy()), right.column("lo").to_numpy(), right.column("hi").to_numpy()
        at = np.searchsorted(codes, lo)
        hit = np.flatnonzero(at < len(codes))
        hit = hit[codes[at[hit]] <= hi[hit]]
        return pa.table({"qid": right.column("qid").take(pa.array(hit)), "key": pa.array(codes[at[hit]], pa.int64())})

    hits = rows.select("run_id", "code").groupBy("run_id").cogroup(renamed(asked, "run_id", "qid", "lo", "hi").groupBy("run_id")).applyInArrow(run, "qid long, key long")
    return hits.groupBy("qid").agg(F.min("key").alias("first_key"))


def filtered_range_scan(rows: DataFrame, asked: DataFrame) -> DataFrame:
    """qid and the rows inside each query, from surviving runs only; queries of a run find theirs by binary search."""
    names = [c for c in rows.columns if c not in ("run_id", "level")]

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        rows_ = left.select(names).sort_by("code")
        codes = rows_.column("code").to_numpy()
        first, last = np.searchsorted(codes, right.column("lo").to_numpy()), np.searchsorted(codes, right.column("hi").to_numpy(), side="right")
        n = np.maximum(last - first, 0)
        owner = np.repeat(np.arange(len(n)), n)
        at = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + first[owner]
        out = rows_.take(pa.array(at))
        return pa.table({"qid": right.column("qid").take(pa.array(owner))} | {c: out.column(c) for c in names})

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields if f.name in names)
    return rows.groupBy("run_id").cogroup(renamed(asked, "run_id", "qid", "lo", "hi").groupBy("run_id")).applyInArrow(run, f"qid long, {kinds}")


def compact(rows: DataFrame, run_rows: int, level: int) -> DataFrame:
    """Runs of all levels merged into one level, keys once, in new ranges; their filters have to be built again."""
    names = [c for c in rows.columns if c not in ("run_id", "level")]
    return balanced_runs(rows.select(*names).dropDuplicates(["code"]), run_rows, level)


def compact_with_filters(rows: DataFrame, sample: DataFrame, space: KeySpace, run_rows: int, level: int, bpk: float = 10, **options) -> tuple[DataFrame, DataFrame]:
    """Merged runs, and their filters tuned on the live sample of queries; the runs are stored first, so that both see one cut."""
    from rangegate.operators.construct import build_run_filters

    merged = compact(rows, run_rows, level)
    path = shared_folder(rows.sparkSession)
    write_store(merged, path)
    merged = read_store(rows.sparkSession, path)
    return merged, build_run_filters(merged, sample, space.bits, bpk, **options)
