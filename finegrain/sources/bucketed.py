"""Bucketed tables: rows hashed and sorted by key once, so that later joins and aggregates by that key need no exchange."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_bucketed(df: DataFrame, table: str, path: str, keys: list[str], buckets: int, sort: list[str] | None = None) -> DataFrame:
    """Write ``df`` as the Parquet table ``table`` below ``path``, bucketed by ``keys``, and read it back.

    Rows are dealt out by the buckets' own hash first, so a bucket is one file and not one for every task.
    """
    dealt = df.repartition(buckets, *keys)
    dealt.write.mode("overwrite").format("parquet").option("path", path).bucketBy(buckets, *keys).sortBy(*(sort or keys)).saveAsTable(table)
    return df.sparkSession.table(table)
