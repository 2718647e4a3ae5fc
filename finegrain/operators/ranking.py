"""Global row numbers without a single-partition window."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_bounds(df: DataFrame, column: str, buckets: int) -> list:
    """At most ``buckets - 1`` ascending cut points of ``column`` from an approximate quantile sketch.

    The sketch and the result are bounded by ``buckets``, not by the rows.
    """
    if buckets < 2:
        return []
    points = [i / buckets for i in range(1, buckets)]
    found = df.agg(F.percentile_approx(column, F.array(*map(F.lit, points)), 20 * buckets).alias("q")).first()["q"]
    return sorted(set(found)) if found else []


def bucket_expr(column: str, bounds: Sequence) -> Column:
    """Number of bounds at or below the value (0 for null), found by a logarithmic chain of comparisons."""

    def pick(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(F.col(column) >= F.lit(bounds[mid]), pick(mid + 1, hi)).otherwise(pick(lo, mid))

    return pick(0, len(bounds)).cast("int")


def global_row_number(df: DataFrame, key: str, ties: Sequence[str], name: str, buckets: int) -> DataFrame:
    """Add ``name``: the row's 0-based position in the order of ``key`` (nulls first), then ``ties``.

    Rows are numbered inside value ranges of ``key``; the sizes of the ranges, one row each, give every
    range its start. Equal rows get consecutive numbers in any order. An empty table gives an empty table.
    """
    bounds = range_bounds(df, key, buckets)
    placed = df.withColumn("_range", bucket_expr(key, bounds))
    order = [F.col(key).asc_nulls_first(), *(F.col(c).asc_nulls_first() for c in ties)]
    local = placed.withColumn("_at", F.row_number().over(Window.partitionBy("_range").orderBy(*order)).cast("long") - 1)
    sizes = placed.groupBy("_range").agg(F.count("*").alias("_n"))
    starts = sizes.select(
        "_range",
        (F.sum("_n").over(Window.orderBy("_range")) - F.col("_n")).alias("_start"),
    )
    # one row per range: bounded by the parameter
    return local.join(F.broadcast(starts), "_range").withColumn(name, F.col("_at") + F.col("_start")).drop("_range", "_at", "_start")


def hash_row_number(df: DataFrame, key: str, ties: Sequence[str], name: str, ranges: int, top: int = 1 << 32) -> DataFrame:
    """As :func:`global_row_number` for a ``key`` that is uniform in ``[0, top)``: its ranges are equal shares, so no pass looks for them."""
    placed = df.withColumn("_range", F.least(F.floor(F.col(key) * F.lit(ranges / top)), F.lit(ranges - 1)).cast("int"))
    order = [F.col(key).asc_nulls_first(), *(F.col(c).asc_nulls_first() for c in ties)]
    local = placed.withColumn("_at", F.row_number().over(Window.partitionBy("_range").orderBy(*order)).cast("long") - 1)
    sizes = placed.groupBy("_range").agg(F.count("*").alias("_n"))
    # one row for each range
    starts = sizes.select("_range", (F.sum("_n").over(Window.orderBy("_range")) - F.col("_n")).alias("_start"))
    return local.join(F.broadcast(starts), "_range").withColumn(name, F.col("_at") + F.col("_start")).drop("_range", "_at", "_start")
