"""Keys from files of any built-in format, and a data source of stored runs that reads only the runs a filter leaves."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.dataset as ds
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThanOrEqual, InputPartition, LessThanOrEqual

KEYS = "run_id long, code long"


def read_keys(spark: SparkSession, path: str, file_format: str = "parquet", schema: str = KEYS) -> DataFrame:
    """Keys of Parquet, ORC, JSON, CSV (with a header) or text (one code a line); the schema is given, so nothing is inferred."""
    if file_format == "text":
        return spark.read.text(path).selectExpr("0L as run_id", "cast(value as long) as code")
    reader = spark.read.schema(schema).format(file_format)
    return (reader.option("header", True) if file_format == "csv" else reader).load(path)


class RunPartition(InputPartition):
    def __init__(self, run_id: int, files: list[str], low: int | None, high: int | None):
        super().__init__(run_id)
        self.run_id, self.files, self.low, self.high = run_id, files, low, high


class RangeStoreReader(DataSourceReader):
    """Takes ``code >= x``, ``code <= x`` and ``run_id = x``; a run whose key range misses them gives no partition."""

    def __init__(self, path: str):
        self.path, self.low, self.high, self.run = path, None, None, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, GreaterThanOrEqual) and f.attribute == ("code",):
                self.low = f.value if self.low is None else max(self.low, f.value)
            elif isinstance(f, LessThanOrEqual) and f.attribute == ("code",):
                self.high = f.value if self.high is None else min(self.high, f.value)
            elif isinstance(f, EqualTo) and f.attribute == ("run_id",):
                self.run = f.value if self.run in (None, f.value) else -1
            else:
                yield f

    def partitions(self) -> list[RunPartition]:
        found: dict[int, list[str]] = {}
        for piece in ds.dataset(self.path, partitioning="hive").get_fragments():
            run_id = int(piece.path.split("run_id=")[1].split("/")[0])
            if self.run is not None and run_id != self.run:
                continue
            stats = [g.statistics.get("code") for g in piece.row_groups]
            ends = [(s["min"], s["max"]) for s in stats if s]
            if len(ends) < len(stats) or any((self.high is None or a <= self.high) and (self.low is None or b >= self.low) for a, b in ends):
                found.setdefault(run_id, []).append(piece.path)
        return [RunPartition(r, files, self.low, self.high) for r, files in sorted(found.items())] or [RunPartition(-1, [], None, None)]

    def read(self, partition: RunPartition) -> Iterator[pa.RecordBatch]:
        for path in partition.files:
            field, test = ds.field("code"), None
            for part in ([field >= partition.low] if partition.low is not None else []) + ([field <= partition.high] if partition.high is not None else []):
                test = part if test is None else test & part
            for batch in ds.dataset(path).scanner(columns=["code"], filter=test).to_batches():
                yield pa.RecordBatch.from_arrays([pa.array([partition.run_id] * batch.num_rows, pa.int64()), batch.column("code").cast(pa.int64())], ["run_id", "code"])


class RangeStore(DataSource):
    """``range_store``: the runs under a mounted folder (option ``path``)."""

    @classmethod
    def name(cls) -> str:
        return "range_store"

    def schema(self) -> str:
        return KEYS

    def reader(self, schema) -> RangeStoreReader:
        return RangeStoreReader(self.options["path"].removeprefix("file://").removeprefix("file:"))


def register(spark: SparkSession) -> None:
    """Makes ``range_store`` known to the session and lets it take filters."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(RangeStore)
