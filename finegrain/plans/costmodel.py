"""Modelled clocks of tree merges and sorts: per-node ready times, idle times, makespans."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain.functions.hashing import fraction, portable_hash
from finegrain.operators.sorter import SortResult
from finegrain.operators.treemerge import depth, merged_level
from finegrain.plans.profile import NetworkProfile
from finegrain.sources.staging import staged


# ------------------------------------------------------------- tree merge


def tree_merge_ns(values: int, workers: int, fan_in: int, p: NetworkProfile) -> float:
    """Time of a merge tree: the local scan, then a hop and the receives of every level."""
    total, left = values / workers * p.scan_ns, workers
    if fan_in <= 1:
        return total + (workers - 1) * (p.hop(workers) + p.receive(1))
    while left > 1:
        total += p.hop(workers) + p.receive(min(fan_in, left))
        left = math.ceil(left / fan_in)
    return total


def tree_merge_table(spark: SparkSession, values: int, workers: int, fan_ins: list[int], p: NetworkProfile) -> DataFrame:
    """``fan_in``, ``depth``, modelled ``ns``."""
    rows = [(f, depth(workers, f), round(tree_merge_ns(values, workers, f, p), 3)) for f in fan_ins]
    return spark.createDataFrame(rows, "fan_in int, depth int, ns double")


def best_tree(spark: SparkSession, values: int, p: NetworkProfile, most_workers: int = 1024) -> DataFrame:
    """Number of workers and fan-in with the least modelled time: the two are chosen together."""
    grid = [(w, f, tree_merge_ns(values, w, f, p)) for w in (2**i for i in range(int(math.log2(most_workers)) + 1)) for f in (1, 2, 4, 8, 16, 32, 64) if f <= max(1, w)]
    return spark.createDataFrame(grid, "workers int, fan_in int, ns double").agg(F.min_by(F.struct("workers", "fan_in", "ns"), "ns").alias("best")).select("best.workers", "best.fan_in", F.round("best.ns", 3).alias("ns"))


def receive_table(loads: DataFrame, p: NetworkProfile, line_gbps: float = 200.0) -> DataFrame:
    """Receive and send time of nodes by their number of ``messages`` and by size: the per-message cost, or the line's where that is slower."""
    sizes = F.explode(F.array(*map(F.lit, (16, 32, 64, 128, 256)))).alias("bytes")
    grid = loads.groupBy("messages").agg(F.count("*").alias("nodes")).select("messages", "nodes", sizes)
    line = F.col("messages") * F.col("bytes") * F.lit(8.0) / F.lit(line_gbps)
    return grid.select(
        "messages",
        "bytes",
        "nodes",
        F.greatest(F.lit(p.first_receive_ns) + (F.col("messages") - 1) * F.lit(p.next_receive_ns), line).alias("receive_ns"),
        F.greatest(F.col("messages") * F.lit(p.send_ns), line).alias("send_ns"),
    )


def sort_ns(n: Column, p: NetworkProfile) -> Column:
    """Local sort of n keys."""
    return F.when(n > 1, F.lit(p.sort_ns) * n * F.log2(n.cast("double"))).otherwise(F.lit(0.0))


# ------------------------------------------------------------- sort


def simulate(result: SortResult, p: NetworkProfile) -> DataFrame:
    """``(level, node, ready_ns, work_ns, comm_ns, idle_ns, done_ns)``.

    A node is ready when its last key has come; it sorts and sends its pivots, waits for the group's pivots, and sends its keys. The
    group's pivots come when the slowest node's have gone up the tree and down again. The last level is the final sort, the one
    after it the values' shuffle, which has no wait.
    """
    cfg = result.config
    nodes = cfg.nodes
    late = lambda *parts: F.when(fraction(portable_hash(cfg.seed, *parts)) < p.tail_share, F.lit(p.tail_ns)).otherwise(F.lit(0.0))
    spark = result.df.sparkSession
    everyone = spark.range(nodes).select(F.col("id").cast("int").alias("node"))
    ready = everyone.withColumn("ready_ns", F.lit(0.0))
    parts = []
    for made in result.levels:
        level, width, b = made.level, cfg.width(made.level), cfg.levels[made.level]
        held = made.routed.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("n"))
        state = ready.join(held, "node", "left").na.fill({"n": 0}).withColumn("grp", F.floor(F.col("node") / F.lit(width)))
        state = state.withColumn("work_ns", sort_ns(F.col("n"), p) + F.lit(p.scan_ns) * F.col("n"))
        sent = F.col("ready_ns") + F.col("work_ns") + F.when(F.col("n") > 0, F.lit((b - 1) * p.send_ns)).otherwise(0.0)
        state = state.withColumn("voted_ns", sent)
        rounds = depth(width, max(2, cfg.fan_in))
        hop = p.hop(width)
        up = rounds * (hop + p.receive(min(cfg.fan_in, width)))
        down = hop + p.receive(b - 1) + (0.0 if p.multicast else width * p.send_ns)
        # a delayed pivot holds up its whole group
        arrival = F.when(F.col("n") > 0, F.col("voted_ns") + late(level, "tail-up", F.col("node"))).otherwise(F.col("ready_ns"))
        groups = state.groupBy("grp").agg((F.max(arrival) + F.lit(up + down)).alias("pivots_ns"))
        state = state.join(groups, "grp").withColumn("idle_ns", F.col("pivots_ns") - F.col("voted_ns"))
        state = state.withColumn("comm_ns", F.lit((b - 1) * p.send_ns + p.receive(b - 1)) + F.col("n") * p.send_ns)
        state = staged(state.withColumn("done_ns", F.col("pivots_ns") + F.col("n") * p.send_ns).withColumn("level", F.lit(level)), "clock")
        parts.append(state.select("level", "node", "ready_ns", "work_ns", "comm_ns", "idle_ns", "done_ns"))
        moves = made.routed.select("src", F.col("node").alias("dst"), late(level, "tail-key", F.col("_rid")).alias("late"))
        moves = moves.join(state.select(F.col("node").alias("src"), "done_ns"), "src")
        far = F.when(F.floor(F.col("src") / p.leaf_nodes) == F.floor(F.col("dst") / p.leaf_nodes), F.lit(p.near_ns)).otherwise(F.lit(p.far_ns))
        got = moves.groupBy(F.col("dst").alias("node")).agg((F.max(F.col("done_ns") + far + F.col("late")) + F.lit(p.first_receive_ns) + (F.count("*") - 1) * F.lit(p.next_receive_ns)).alias("ready_ns"))
        # a node that gets no key still knows that the level is over when its group's pivots were sent
        fallback = state.select("node", "done_ns")
        ready = fallback.join(got, "node", "left").select("node", F.coalesce("ready_ns", "done_ns").alias("ready_ns"))
    held = result.df.groupBy("node").agg(F.count("*").alias("n"))
    last = ready.join(held, "node", "left").na.fill({"n": 0}).withColumn("work_ns", sort_ns(F.col("n"), p)).withColumn("done_ns", F.col("ready_ns") + F.col("work_ns"))
    final = last.select(F.lit(len(result.levels)).alias("level"), "node", "ready_ns", "work_ns", F.lit(0.0).alias("comm_ns"), F.lit(0.0).alias("idle_ns"), "done_ns")
    shuffle = F.col("n") * F.lit(p.send_ns) + F.lit(2 * p.hop(nodes)) + F.col("n") * F.lit(p.next_receive_ns * p.record_bytes / p.key_bytes)
    values = last.select(F.lit(len(result.levels) + 1).alias("level"), "node", F.col("done_ns").alias("ready_ns"), F.lit(0.0).alias("work_ns"), shuffle.alias("comm_ns"), F.lit(0.0).alias("idle_ns"), (F.col("done_ns") + shuffle).alias("done_ns"))
    return reduce(DataFrame.unionByName, [*parts, final, values])


def simulate_boundary_sort(placed: DataFrame, routed: DataFrame, nodes: int, reduction_factor: int, per_node: int, p: NetworkProfile) -> DataFrame:
    """Clock of the boundary-first sort: ``(step, node, ready_ns, done_ns)`` of the local sort, every level of pivot sorters, and the final sort.

    Every node sorts its keys and sends its samples; a pivot sorter waits for its ``reduction_factor`` senders, takes their keys one
    by one, sorts them and sends its own on; the root sends the ``nodes - 1`` boundaries to every node (to all at once only where the network
    multicasts); keys then go out and are sorted where they arrive.
    """
    everyone = placed.sparkSession.range(nodes).select(F.col("id").cast("int").alias("node"))
    held = everyone.join(placed.groupBy("node").agg(F.count("*").alias("n")), "node", "left").na.fill({"n": 0})
    local = held.withColumn("ready_ns", F.lit(0.0)).withColumn("done_ns", sort_ns(F.col("n"), p) + F.lit(p.scan_ns) * F.col("n") + F.lit(per_node * p.send_ns))
    parts = [local.select(F.lit(0).alias("step"), "node", "ready_ns", "done_ns")]
    state, size, left = local.select("node", "done_ns"), per_node, nodes
    for step in range(1, depth(nodes, reduction_factor) + 1):
        hop, left = p.hop(min(nodes, reduction_factor**step)), -(-left // reduction_factor)
        forward = nodes - 1 if left == 1 else min(nodes - 1, per_node * reduction_factor**step)
        got = state.groupBy(F.floor(F.col("node") / reduction_factor).cast("int").alias("node")).agg((F.max("done_ns") + F.lit(hop)).alias("ready_ns"), (F.count("*") * size).alias("n"))
        work = F.lit(p.first_receive_ns) + (F.col("n") - 1) * F.lit(p.next_receive_ns) + sort_ns(F.col("n"), p) + F.lit(forward * p.send_ns)
        state = got.withColumn("done_ns", F.col("ready_ns") + work)
        parts.append(state.select(F.lit(step).alias("step"), "node", "ready_ns", "done_ns"))
        size = forward
    copies = 1 if p.multicast else nodes
    told = state.select((F.col("done_ns") + F.lit((nodes - 1) * (copies - 1) * p.send_ns + p.hop(nodes) + p.receive(nodes - 1))).alias("told_ns"))
    came = routed.groupBy("node").agg(F.count("*").alias("got"))
    last = held.join(came, "node", "left").na.fill({"got": 0}).crossJoin(F.broadcast(told))  # one row
    arrive = F.col("told_ns") + F.max(F.col("n") * p.send_ns).over(Window.partitionBy(F.lit(0))) + F.lit(p.hop(nodes)) + F.col("got") * F.lit(p.next_receive_ns)  # a row a node
    last = last.withColumn("ready_ns", arrive).withColumn("done_ns", F.col("ready_ns") + sort_ns(F.col("got"), p))
    parts.append(last.select(F.lit(len(parts)).alias("step"), "node", "ready_ns", "done_ns"))
    return reduce(DataFrame.unionByName, parts)


def makespan(clock: DataFrame) -> DataFrame:
    """End of the sort and of the values' shuffle, total idle time, compute to communication."""
    last = clock.agg(F.max("level").alias("m")).first()["m"]
    return clock.agg(
        F.max(F.when(F.col("level") == last - 1, F.col("done_ns"))).alias("sort_ns"),
        F.max("done_ns").alias("total_ns"),
        F.avg("idle_ns").alias("mean_idle_ns"),
        (F.sum("work_ns") / F.sum("comm_ns")).alias("compute_to_comm"),
    )


def breakdown(clock: DataFrame) -> DataFrame:
    """Distribution over nodes of each level's time and idle time."""
    spent = (F.col("done_ns") - F.col("ready_ns")).alias("spent")
    q = lambda c, x: F.percentile(c, F.lit(x))
    return clock.select("level", spent, "idle_ns").groupBy("level").agg(
        F.min("spent").alias("least"), q("spent", 0.25).alias("p25"), q("spent", 0.5).alias("p50"), q("spent", 0.75).alias("p75"), F.max("spent").alias("most"),
        F.stddev_pop("spent").alias("spread"), F.avg("idle_ns").alias("idle_mean"), F.max("idle_ns").alias("idle_most"),
    )


def waits(clock: DataFrame) -> DataFrame:
    """Each node's wait between the end of one level and the start of the next."""
    over = Window.partitionBy("node").orderBy("level")
    return clock.withColumn("wait_ns", F.col("ready_ns") - F.lag("done_ns").over(over)).select("level", "node", "wait_ns")


def reorder_depth(clock: DataFrame, messages: DataFrame, p: NetworkProfile) -> DataFrame:
    """Messages of a level that reach a node before the node is done with that level's own sending: what a reordering buffer holds.

    A message arrives a hop after its sender has sent (inside a leaf or across) and takes a receive. Messages in ``messages`` are sums over
    a pair of nodes, which share their time; delays of single messages are not in them.
    """
    times = clock.select("level", "node", "done_ns")
    sent = messages.join(times.select("level", F.col("node").alias("src"), F.col("done_ns").alias("sent_ns")), ["level", "src"])
    own = times.select("level", F.col("node").alias("dst"), F.col("done_ns").alias("busy_ns"))
    hop = F.when(F.floor(F.col("src") / p.leaf_nodes) == F.floor(F.col("dst") / p.leaf_nodes), F.lit(p.near_ns)).otherwise(F.lit(p.far_ns))
    early = F.col("sent_ns") + hop + F.lit(p.first_receive_ns) < F.col("busy_ns")
    return sent.join(own, ["level", "dst"]).groupBy("level").agg(F.sum(F.when(early, F.col("n_msgs")).otherwise(0)).alias("early"), F.sum("n_msgs").alias("n_msgs"))


def graph_shape(partials: DataFrame, workers: int, fan_in: int) -> DataFrame:
    """Level and number of tasks of a merge tree over the workers' ``partials``: its width and depth."""
    rounds = [partials]
    for _ in range(depth(workers, fan_in)):
        rounds.append(merged_level(rounds[-1], fan_in))
    counts = [r.agg(F.count("*").alias("tasks")).select(F.lit(level).alias("level"), "tasks") for level, r in enumerate(rounds)]
    return reduce(DataFrame.unionByName, counts)
