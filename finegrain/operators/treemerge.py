"""Merges along a tree with a chosen fan-in."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Reducers as (local, merge) pairs of aggregates.
REDUCERS: dict[str, tuple[Callable, Callable]] = {
    "min": (F.min, F.min),
    "max": (F.max, F.max),
    "sum": (F.sum, F.sum),
    "count": (F.count, F.sum),
    "bit_or": (F.bit_or, F.bit_or),
    "bit_and": (F.bit_and, F.bit_and),
    "hll": (F.hll_sketch_agg, F.hll_union_agg),
}


def depth(workers: int, fan_in: int) -> int:
    """Merge levels of a tree over so many workers; fan-in 1 is a chain."""
    if workers <= 1:
        return 0
    if fan_in <= 1:
        return workers - 1
    levels, left = 0, workers
    while left > 1:
        left, levels = math.ceil(left / fan_in), levels + 1
    return levels


def assigned(df: DataFrame, position: str, workers: int) -> DataFrame:
    """Add ``worker``: the row's position modulo the number of workers."""
    return df.withColumn("worker", F.pmod(F.col(position).cast("long"), F.lit(workers)).cast("int"))


def local_partials(df: DataFrame, value: str, agg: str = "min", by: Sequence[str] = ()) -> DataFrame:
    """Every worker's own partial."""
    return df.groupBy(*by, F.col("worker").alias("idx")).agg(REDUCERS[agg][0](value).alias("v"))


def merged_level(partials: DataFrame, fan_in: int, agg: str = "min", by: Sequence[str] = ()) -> DataFrame:
    """One level of the tree: ``fan_in`` neighbours merge into one."""
    return partials.groupBy(*by, F.floor(F.col("idx") / F.lit(fan_in)).cast("int").alias("idx")).agg(REDUCERS[agg][1]("v").alias("v"))


def _chain(partials: DataFrame, agg: str, by: Sequence[str]) -> DataFrame:
    """Fan-in 1: worker after worker, in order, as one ordered fold over the partials (as many as workers)."""
    fold: dict[str, Callable[[Column, Column], Column]] = {"min": lambda a, x: F.least(a, x), "max": lambda a, x: F.greatest(a, x), "sum": lambda a, x: a + x, "count": lambda a, x: a + x, "bit_or": lambda a, x: a.bitwiseOR(x), "bit_and": lambda a, x: a.bitwiseAND(x)}
    if agg not in fold:
        raise ValueError(f"no chain for {agg}")
    ordered = partials.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("idx", "v"))).alias("all"))
    values = F.transform("all", lambda x: x["v"])
    return ordered.select(*by, F.lit(0).alias("idx"), F.aggregate(F.slice(values, 2, F.size(values)), values[0], fold[agg]).alias("v"))


def tree_merge(df: DataFrame, value: str, position: str, workers: int, fan_in: int, agg: str = "min", by: Sequence[str] = (), levels: bool = False) -> DataFrame:
    """Merge ``value`` over ``workers`` along a tree of ``fan_in``; one row for each ``by``.

    ``levels=True`` returns the partials of all levels with their ``level`` instead.
    """
    partials = local_partials(assigned(df, position, workers), value, agg, by)
    if fan_in <= 1:
        return _chain(partials, agg, by).withColumnRenamed("v", value).drop("idx")
    rounds = [partials.withColumn("level", F.lit(0))]
    left, level = workers, 0
    while left > 1:
        partials, left, level = merged_level(partials, fan_in, agg, by), math.ceil(left / fan_in), level + 1
        rounds.append(partials.withColumn("level", F.lit(level)))
    if levels:
        out = rounds[0]
        for r in rounds[1:]:
            out = out.unionByName(r)
        return out
    return partials.drop("idx").withColumnRenamed("v", value)
