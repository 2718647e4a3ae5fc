"""Relational operators that users of the sorter need and Spark lacks or leaves to hints."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def bucket_range_join(rows: DataFrame, ranges: DataFrame, key: str, low: str = "lo", high: str = "hi", most_broadcast: int = 100_000) -> DataFrame:
    """Rows with the half-open range ``[lo, hi)`` that holds their key; a null bound is open.

    Up to ``most_broadcast`` ranges the ranges are broadcast; beyond it both sides are dealt out by coarse ranges of the key.
    """
    inside = (F.col(low).isNull() | (F.col(key) >= F.col(low))) & (F.col(high).isNull() | (F.col(key) < F.col(high)))
    if ranges.count() <= most_broadcast:
        return rows.join(F.broadcast(ranges), inside)
    from finegrain.operators.ranking import bucket_expr, range_bounds

    bounds = range_bounds(rows, key, 256)
    cells = ranges.withColumn("_a", F.when(F.col(low).isNull(), 0).otherwise(bucket_expr(low, bounds))).withColumn("_b", F.when(F.col(high).isNull(), len(bounds)).otherwise(bucket_expr(high, bounds)))
    cells = cells.withColumn("_cell", F.explode(F.sequence("_a", "_b"))).drop("_a", "_b")
    return rows.withColumn("_cell", bucket_expr(key, bounds)).join(cells, "_cell").filter(inside).drop("_cell")


def as_of_join(left: DataFrame, right: DataFrame, on: str, by: Sequence[str], values: Sequence[str]) -> DataFrame:
    """Each left row with the last right row at or before it in ``on``, within ``by``: one union and one window, no inequality join."""
    pad = [F.lit(None).cast(left.schema[c].dataType).alias(c) if c not in (*by, on) else F.col(c) for c in left.columns]
    facts = F.struct(*(F.col(v) for v in values))
    merged = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.select(facts.alias("x")).schema["x"].dataType)).unionByName(right.select(*pad, F.lit(0).alias("_side"), facts.alias("_v")))
    over = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    last = merged.withColumn("_last", F.last("_v", ignorenulls=True).over(over)).filter("_side = 1")
    return last.select(*left.columns, *(F.col("_last")[v].alias(f"{v}_asof") for v in values))


def interval_join(left: DataFrame, right: DataFrame, left_time: str, right_time: str, by: Sequence[str], seconds: int) -> DataFrame:
    """Pairs within ``by`` whose times differ by ``seconds`` at most, by cells of that length: each left row meets three cells."""
    cell = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    near = left.withColumn("_cell", F.explode(F.array(cell(left_time) - 1, cell(left_time), cell(left_time) + 1)))
    met = near.join(right.withColumn("_cell", cell(right_time)), [*by, "_cell"]).drop("_cell")
    gap = F.unix_micros(F.col(left_time).cast("timestamp")) - F.unix_micros(F.col(right_time).cast("timestamp"))
    return met.filter(F.abs(gap) <= seconds * 1_000_000)


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16, how: str = "inner") -> DataFrame:
    """Equi-join that spreads each key of ``left`` over ``salts`` tasks and repeats ``right`` as often (inner and left joins)."""
    spread = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    repeated = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return spread.join(repeated, [key, "_salt"], how).drop("_salt")


def grouping_totals(df: DataFrame, kind: str, keys: Sequence[str], *aggs: Column) -> DataFrame:
    """``rollup``, ``cube`` or plain ``groupBy`` by name."""
    return {"rollup": df.rollup, "cube": df.cube, "group": df.groupBy}[kind](*keys).agg(*aggs)


def histogram(df: DataFrame, value: str, low: float, high: float, bins: int) -> DataFrame:
    """Rows by equal-width bin: 1 to ``bins``, 0 below and ``bins + 1`` above."""
    return df.groupBy(F.width_bucket(F.col(value), F.lit(low), F.lit(high), F.lit(bins)).alias("bin")).agg(F.count("*").alias("n"))
