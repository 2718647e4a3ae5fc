"""Where keys go: the initial spread over nodes, routing into a bucket's nodes, and the counted alternative."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from finegrain.functions.hashing import HASHES
from finegrain.operators.ranking import hash_row_number

#: Rows that one range of the exact placement is meant to hold.
RANGE_ROWS = 50_000


def initial_shuffle(df: DataFrame, nodes: int, seed: int, how: str = "exact", hash_name: str = "portable") -> DataFrame:
    """Add ``node`` and ``origin_node`` to rows with ``_rid``.

    ``exact``: equal numbers, in hash order (a distributed ranking over as many ranges as the rows need). ``hash``: by hash alone. ``round_robin``: ``repartition``
    and the partition's number, for physical runs.
    """
    h = HASHES[hash_name]
    if how == "exact":
        ranges = max(8, df.count() // RANGE_ROWS)
        ranked = hash_row_number(df.withColumn("_h", h(seed, 0, "init", F.col("_rid"))), "_h", ["_rid"], "_rn", ranges)
        out = ranked.withColumn("node", F.pmod("_rn", F.lit(nodes)).cast("int")).drop("_h", "_rn")
    elif how == "hash":
        out = df.withColumn("node", F.pmod(h(seed, 0, "init", F.col("_rid")), F.lit(nodes)).cast("int"))
    elif how == "round_robin":
        out = df.repartition(nodes).withColumn("node", F.spark_partition_id())
    else:
        raise ValueError(how)
    return out.withColumn("origin_node", F.col("node"))


def bucket_of(key: str | Column, pivots: str | Column, count: int) -> Column:
    """Number of the ``count`` ascending pivots at or below the key, by bisection: a step for each bit of ``count``."""
    key, pivots = (F.col(x) if isinstance(x, str) else x for x in (key, pivots))
    steps = [1 << i for i in reversed(range(max(1, count).bit_length()))]
    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), lambda at, step: F.when(F.get(pivots, at + step - 1) <= key, at + step).otherwise(at))


def route(df: DataFrame, level: int, width: int, buckets: int, seed: int, hash_name: str = "portable") -> DataFrame:
    """Add ``bucket`` and ``src`` and move ``node`` to a random node of the bucket's equal share of the group's ``width`` nodes."""
    share = width // buckets
    draw = HASHES[hash_name](seed, level, "route", F.col("_rid"))
    bucketed = df.withColumn("bucket", bucket_of("k", "pivots", buckets - 1)).withColumn("src", F.col("node"))
    target = F.col("grp") * width + F.col("bucket") * share + F.pmod(draw, F.lit(share))
    return bucketed.withColumn("node", target.cast("int"))


def proportional(counts: DataFrame, nodes: int) -> DataFrame:
    """Baseline: nodes in proportion to bucket counts (``bucket``, ``n``), one at least: ``first_node``, ``n_nodes``.

    ``counts`` has one row for each bucket.
    """
    over = Window.orderBy("bucket")
    total = F.sum("n").over(Window.partitionBy())
    before = F.sum("n").over(over) - F.col("n")
    first = F.floor(before * nodes / total).cast("int")
    last = F.greatest(first, F.ceil((before + F.col("n")) * nodes / total).cast("int") - 1)
    return counts.select("bucket", "n", first.alias("first_node"), (last - first + 1).alias("n_nodes"))
