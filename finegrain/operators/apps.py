"""Sketches of applications on top of the sorter and the merge tree."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.functions.keys import KeySpec
from finegrain.operators.microtasks import word_ids
from finegrain.operators.sorter import SortConfig, SortResult, recursive_sort
from finegrain.operators.treemerge import tree_merge


def map_reduce(df: DataFrame, transform: Column, position: str, workers: int, fan_in: int, agg: str = "sum") -> DataFrame:
    """Transform every row, then merge along a tree."""
    return tree_merge(df.withColumn("mapped", transform), "mapped", position, workers, fan_in, agg)


def morton_code(columns: Sequence[Column], bits: int = 8) -> Column:
    """Interleaved bits of non-negative integers below ``2**bits``: close points get close codes."""
    code = F.lit(0).cast("long")
    for bit in range(bits):
        for d, c in enumerate(columns):
            one = F.shiftright(c.cast("long"), bit).bitwiseAND(F.lit(1))
            code = code.bitwiseOR(F.shiftleft(one, bit * len(columns) + d))
    return code


def zorder_sort(df: DataFrame, vector: str, id_col: str, dimensions: int, cfg: SortConfig, bits: int = 8, low: float = -4.0, high: float = 4.0) -> SortResult:
    """Objects in the order of a space-filling curve, as a hierarchy of bounding volumes wants them."""
    cell = lambda i: F.greatest(F.lit(0), F.least(F.lit(2**bits - 1), F.floor((F.col(vector)[i] - low) / (high - low) * 2**bits))).cast("long")
    coded = df.select(id_col, morton_code([cell(i) for i in range(dimensions)], bits).alias("code"))
    return recursive_sort(coded, KeySpec.of("code", id_col), cfg)


def bounding_boxes(ranked: DataFrame, vectors: DataFrame, id_col: str, vector: str, dimensions: int, leaf: int) -> DataFrame:
    """Leaves of ``leaf`` consecutive objects with their boxes."""
    joined = ranked.select(id_col, "rank").join(vectors.select(id_col, vector), id_col).withColumn("leaf", F.floor(F.col("rank") / leaf))
    bounds = [f(F.col(vector)[i]).alias(f"{n}{i}") for i in range(dimensions) for n, f in (("lo", F.min), ("hi", F.max))]
    return joined.groupBy("leaf").agg(F.count("*").alias("n"), *bounds)


def boolean_search(docs: DataFrame, id_col: str, text: str, all_of: list[str], none_of: Sequence[str] = (), any_of: Sequence[str] = ()) -> DataFrame:
    """Ids of documents that hold all, none and some of the given words, by set algebra on word-id rows."""
    wanted = [*all_of, *none_of, *any_of]
    hits = word_ids(docs, id_col, text).filter(F.col("word").isin(wanted)).groupBy("id").agg(F.collect_set("word").alias("w"))
    has: Callable[[str], Column] = lambda word: F.array_contains("w", word)
    keep = F.lit(True)
    for word in all_of:
        keep = keep & has(word)
    for word in none_of:
        keep = keep & ~has(word)
    if any_of:
        some = F.lit(False)
        for word in any_of:
            some = some | has(word)
        keep = keep & some
    return hits.filter(keep).select("id")
