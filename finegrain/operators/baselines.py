"""What the recursive sort and the merge tree are compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from finegrain.functions.hashing import HASHES
from finegrain.functions.keys import KeySpec
from finegrain.operators.placement import bucket_of, initial_shuffle
from finegrain.operators.sorter import attach_pivots, global_rank, keyed_rows
from finegrain.operators.treemerge import depth
from finegrain.sources.staging import staged

#: Boundaries up to this number go to every row as one array.
FEW_CUTS = 1024


def node_samples(placed: DataFrame, per_node: int) -> DataFrame:
    """``(idx, keys)``: of every node ``per_node`` evenly spaced keys of its sorted ones."""
    lists = placed.groupBy(F.col("node").alias("idx")).agg(F.sort_array(F.collect_list("k")).alias("all"))
    return lists.select("idx", _spaced("all", per_node).alias("keys"))


def _spaced(column: str, n: int):
    size = F.size(column).cast("long")  # the place times the size goes beyond 32 bits
    return F.transform(F.sequence(F.lit(1), F.lit(n)), lambda j: F.element_at(column, F.greatest(F.lit(1), F.ceil(j * size / F.lit(float(n + 1))).cast("int"))))


def reduced_samples(samples: DataFrame, nodes: int, reduction_factor: int, per_node: int, rounds: bool = False) -> DataFrame:
    """Levels of pivot sorters: each sorts what ``reduction_factor`` others send and forwards as many evenly spaced keys as one
    sent, times the factor's share that keeps ``nodes - 1`` boundaries apart at the root."""
    seen, left = [samples.withColumn("level", F.lit(0))], nodes
    for level in range(1, depth(nodes, reduction_factor) + 1):
        left = -(-left // reduction_factor)
        forward = nodes - 1 if left == 1 else min(nodes - 1, per_node * reduction_factor**level)
        merged = samples.select(F.floor(F.col("idx") / reduction_factor).cast("int").alias("idx"), F.explode("keys").alias("p")).groupBy("idx").agg(F.sort_array(F.collect_list("p")).alias("all"))
        samples = merged.select("idx", _spaced("all", forward).alias("keys"))
        seen.append(samples.withColumn("level", F.lit(level)))
    if rounds:
        out = seen[0]
        for s in seen[1:]:
            out = out.unionByName(s)
        return out
    return samples


def boundaries(placed: DataFrame, nodes: int, reduction_factor: int, per_node: int) -> DataFrame:
    """One row with the ``nodes - 1`` ascending bucket boundaries."""
    root = reduced_samples(node_samples(placed, per_node), nodes, reduction_factor, per_node)
    return root.select(F.col("keys").alias("pivots"))  # spaced out of sorted ones


def boundary_sort(df: DataFrame, key: KeySpec, nodes: int, reduction_factor: int = 4, per_node: int = 32, seed: int = 7, hash_name: str = "portable") -> DataFrame:
    """Boundary-first sort: boundaries of all buckets first, then every record is routed once and sorted where it arrives."""
    return global_rank(boundary_run(df, key, nodes, reduction_factor, per_node, seed, hash_name)[1], nodes).drop("_rid")


def boundary_run(df: DataFrame, key: KeySpec, nodes: int, reduction_factor: int = 4, per_node: int = 32, seed: int = 7, hash_name: str = "portable") -> tuple[DataFrame, DataFrame]:
    """The keys as they were placed and as the boundary-first sort routes them."""
    placed = placed_keys(df, key, nodes, seed, hash_name)
    return placed, routed_by_boundaries(placed, nodes, reduction_factor, per_node)


def placed_keys(df: DataFrame, key: KeySpec, nodes: int, seed: int = 7, hash_name: str = "portable") -> DataFrame:
    """The keys on their first nodes, which no reduction factor changes."""
    return staged(initial_shuffle(keyed_rows(df, key), nodes, seed, "exact", hash_name), "placed")


def routed_by_boundaries(placed: DataFrame, nodes: int, reduction_factor: int, per_node: int = 32) -> DataFrame:
    """Placed keys on the nodes that the boundaries give them."""
    cuts = staged(boundaries(placed, nodes, reduction_factor, per_node), "boundaries")
    return staged(cut_rows(placed, cuts, nodes - 1).withColumnRenamed("bucket", "node"), "routed")


def cut_rows(rows: DataFrame, cuts: DataFrame, count: int) -> DataFrame:
    """``rows`` (``k``; an old ``node`` goes) with ``bucket``, the number of the ``count`` ascending ``pivots`` in the one row of ``cuts`` at or below the key.

    A join hands every row its own copy of the pivots, so many of them come in two steps: every ``step``-th one first, then those
    between two of these, about ``sqrt(count)`` each.
    """
    rows = rows.drop("node")
    if count <= FEW_CUTS:
        return attach_pivots(rows.withColumn("grp", F.lit(0)), cuts.withColumn("grp", F.lit(0)), 1).withColumn("bucket", bucket_of("k", "pivots", count)).drop("pivots", "grp")
    step = math.isqrt(count) + 1
    blocks = count // step
    coarse = cuts.select(F.lit(0).alias("_all"), F.transform(F.sequence(F.lit(1), F.lit(blocks)), lambda i: F.element_at("pivots", i * step)).alias("_coarse"))
    fine = staged(cuts.select(F.posexplode("pivots").alias("_j", "p")).groupBy(F.floor(F.col("_j") / step).cast("int").alias("_block")).agg(F.sort_array(F.collect_list("p")).alias("_fine")), "cuts")
    blocked = rows.withColumn("_all", F.lit(0)).join(F.broadcast(coarse), "_all", "left").withColumn("_block", bucket_of("k", "_coarse", blocks)).drop("_all", "_coarse")
    inside = F.when(F.col("_fine").isNull(), 0).otherwise(bucket_of("k", "_fine", step))
    return blocked.join(F.broadcast(fine), "_block", "left").withColumn("bucket", F.col("_block") * step + inside).drop("_block", "_fine")


def single_scan_min(df: DataFrame, value: str) -> DataFrame:
    """One worker that scans everything."""
    return df.select(value).coalesce(1).agg(F.min(value).alias(value))


def single_sort(df: DataFrame, *order: str) -> DataFrame:
    """One worker that sorts everything; ``rank`` from 0."""
    return df.coalesce(1).withColumn("rank", (F.row_number().over(Window.orderBy(*order)) - 1).cast("long"))


def builtin_sort(df: DataFrame, *order) -> DataFrame:
    """Spark's own global sort: range partitions from a sample, one shuffle."""
    return df.orderBy(*order)


def global_random_pivots(df: DataFrame, key: KeySpec, buckets: int, seed: int = 7) -> DataFrame:
    """``buckets - 1`` keys drawn from the whole key set, one draw for all nodes: ``(j, k, rid)``."""
    rows = keyed_rows(df, key).withColumn("_h", HASHES["portable"](seed, 0, "draw", F.col("_rid")))
    drawn = rows.orderBy("_h", "_rid").limit(buckets - 1)
    return drawn.withColumn("j", F.row_number().over(Window.orderBy("k")).cast("int")).drop("_h")
