"""Benchmark records (8-byte key, 96-byte value) as expressions and as a Python data source, and other readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from finegrain.functions.hashing import fast_hash


def records(spark: SparkSession, rows: int, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """Random records: ``rid``, ``key`` (64 bits) and ``payload`` (96 characters), the same at any number of partitions."""
    ids = spark.range(0, rows, 1, partitions) if partitions else spark.range(rows)
    return ids.select(F.col("id").alias("rid"), F.xxhash64(F.lit(seed), "id").alias("key"), F.rpad(F.hex(fast_hash(seed, F.col("id"))), 96, "x").alias("payload"))


class RecordSource(DataSource):
    """``spark.read.format("finegrain_records").option("rows", n)``: the same layout from a Python data source."""

    @classmethod
    def name(cls) -> str:
        return "finegrain_records"

    def schema(self) -> str:
        return "rid long, key long, payload string"

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return _RecordReader(self.options)


class _RecordReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.parts = int(options.get("rows", "1000")), int(options.get("partitions", "4"))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for rid in range(partition.value, self.rows, self.parts):
            key = (rid * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) % 2**64
            yield rid, key - 2**64 if key >= 2**63 else key, f"{key:016x}".ljust(96, "x")


def read(spark: SparkSession, kind: str, path: str, schema: T.StructType | str) -> DataFrame:
    """CSV, JSON, ORC, Parquet or text with a given schema: nothing is inferred."""
    return spark.read.format(kind).schema(schema).options(**({"header": "true"} if kind == "csv" else {})).load(path)


def write(df: DataFrame, kind: str, path: str) -> None:
    df.write.format(kind).options(**({"header": "true"} if kind == "csv" else {})).save(path)
