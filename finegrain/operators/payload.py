"""Values follow their sorted keys: late materialisation and sorted output."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.functions.keys import KeySpec


def redistribute(ranked: DataFrame, records: DataFrame, key: KeySpec) -> DataFrame:
    """Join the records' other columns to the ranked keys by record id."""
    own = set(ranked.columns)
    values = records.select(*key.rid, *(c for c in records.columns if c not in own))
    return ranked.join(values, list(key.rid))


def sorted_partitions(ranked: DataFrame, rows_per_partition: int, most: int = 4096) -> DataFrame:
    """Partitions that hold consecutive ranks, each in order."""
    total = ranked.count()
    parts = max(1, min(most, -(-total // rows_per_partition)))
    place = F.floor(F.col("rank") * parts / F.lit(max(1, total))).cast("int")
    return ranked.repartitionById(parts, place).sortWithinPartitions("rank")


def write_sorted(ranked: DataFrame, path: str, rows_per_file: int, key_columns: Sequence[str]) -> None:
    """Sorted Parquet in two regions, keys and values, whose files hold the same ranks in the same order."""
    parts = sorted_partitions(ranked, rows_per_file)
    keys = [c for c in parts.columns if c in (*key_columns, "rank")]
    values = [c for c in parts.columns if c not in key_columns and c != "k"]
    parts.select(*keys).write.option("maxRecordsPerFile", rows_per_file).parquet(f"{path}/keys")
    parts.select(*values).write.option("maxRecordsPerFile", rows_per_file).parquet(f"{path}/values")


def range_lookup(spark, path: str, column: str, low, high) -> DataFrame:
    """Rows of sorted output in a closed range; the files' statistics prune the others."""
    return spark.read.parquet(path).filter(F.col(column).between(low, high))
