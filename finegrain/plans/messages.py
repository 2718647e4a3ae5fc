"""Ledgers of messages: what a run sends, by level and phase."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain.operators.sorter import SortResult
from finegrain.plans.profile import NetworkProfile

SCHEMA = "level int, phase string, n_msgs long, n_bytes long"


def planned_ledger(spark: SparkSession, nodes: int, keys: int, radices: tuple[int, ...], profile: NetworkProfile, preloaded: bool = False) -> DataFrame:
    """Messages of a run in which every node has keys, in closed form.

    Every node sends each of its pivots to that pivot's tree; roots send pivots one by one, to the group at once where the
    network multicasts, else to each node.
    """
    rows = [] if preloaded else [(-1, "initial", keys, keys * profile.key_bytes)]
    groups = 1
    for level, b in enumerate(radices):
        up = (b - 1) * nodes
        down = (b - 1) * (groups if profile.multicast else nodes)
        rows += [(level, "pivots_up", up, up * profile.pivot_bytes), (level, "pivots_down", down, down * profile.pivot_bytes), (level, "keys", keys, keys * profile.key_bytes)]
        groups *= b
    rows.append((len(radices), "payload", keys, keys * profile.record_bytes))
    return spark.createDataFrame(rows, SCHEMA)


def measured_ledger(result: SortResult, profile: NetworkProfile, preloaded: bool = False) -> DataFrame:
    """Messages of a run as it went: nodes without keys send no pivots."""
    parts = []
    placed = result.placed.agg(F.count("*").alias("n_msgs"))
    if not preloaded:
        parts.append(placed.select(F.lit(-1).alias("level"), F.lit("initial").alias("phase"), "n_msgs"))
    for made in result.levels:
        b, width = result.config.levels[made.level], result.config.width(made.level)
        nodes = made.local.filter("pivots is not null").groupBy("grp").agg(F.count("*").alias("n"))
        up = nodes.agg(F.coalesce(F.sum(F.col("n") * (b - 1)), F.lit(0)).alias("n_msgs"))
        down = nodes.agg((F.count("*") * (b - 1) * (1 if profile.multicast else width)).alias("n_msgs"))
        keys = made.routed.agg(F.count("*").alias("n_msgs"))
        parts += [x.select(F.lit(made.level).alias("level"), F.lit(phase).alias("phase"), F.col("n_msgs").cast("long")) for phase, x in (("pivots_up", up), ("pivots_down", down), ("keys", keys))]
    parts.append(result.df.agg(F.count("*").alias("n_msgs")).select(F.lit(len(result.levels)).alias("level"), F.lit("payload").alias("phase"), "n_msgs"))
    size = F.when(F.col("phase") == "payload", profile.record_bytes).when(F.col("phase").isin("pivots_up", "pivots_down"), profile.pivot_bytes).otherwise(profile.key_bytes)
    return reduce(DataFrame.unionByName, parts).withColumn("n_bytes", (F.col("n_msgs") * size).cast("long"))


def key_messages(result: SortResult) -> DataFrame:
    """``(level, src, dst, n_msgs)`` of the keys' moves; source and destination share a group."""
    parts = [made.routed.groupBy("src", F.col("node").alias("dst")).agg(F.count("*").alias("n_msgs")).withColumn("level", F.lit(made.level)) for made in result.levels]
    return reduce(DataFrame.unionByName, parts).select("level", "src", "dst", "n_msgs")


def traffic(ledger: DataFrame) -> DataFrame:
    """Messages and bytes by level and phase with all subtotals."""
    return ledger.cube("level", "phase").agg(F.sum("n_msgs").alias("n_msgs"), F.sum("n_bytes").alias("n_bytes"))


def node_load(messages: DataFrame) -> DataFrame:
    """Most and mean messages that nodes send and get at each level."""
    sent = messages.groupBy("level", F.col("src").alias("node")).agg(F.sum("n_msgs").alias("n")).withColumn("side", F.lit("sent"))
    got = messages.groupBy("level", F.col("dst").alias("node")).agg(F.sum("n_msgs").alias("n")).withColumn("side", F.lit("received"))
    return sent.unionByName(got).groupBy("level", "side").agg(F.max("n").alias("most"), F.avg("n").alias("mean"))
