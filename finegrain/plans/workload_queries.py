"""Registered queries of merge trees, cost models, experiment workloads, small tasks and applications."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain.functions.hashing import fast_hash
from finegrain.functions.keys import KeySpec
from finegrain.functions.pivots import expected_buckets, median_quantile
from finegrain.functions.udfs import median_element
from finegrain.operators import apps, baselines, microtasks
from finegrain.operators.mediantree import best_fan_in, median_tree
from finegrain.operators.ranking import hash_row_number
from finegrain.operators.sorter import SortConfig, recursive_sort
from finegrain.operators.treemerge import assigned, depth, local_partials, tree_merge
from finegrain.plans import costmodel, measures, messages
from finegrain.plans.profile import PRESETS, NetworkProfile
from finegrain.sources.staging import staged
from finegrain.sources.tables import load

Query = Callable[[SparkSession, str], DataFrame]

PUBLISHED_TREE, SIMULATED = PRESETS["tree_merge_published"], PRESETS["simulated"]
EVENT_KEY = KeySpec.of("value", "event_id")
ORDER_KEY = KeySpec.of("o_totalprice", "o_orderkey")
SIZED_KEY = KeySpec.of("price", "rid")
LINE_ID = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


def _events(spark: SparkSession, sf_dir: str, n: int, *columns: str) -> DataFrame:
    return load(spark, sf_dir, "events", ["event_id", *(columns or ("value",))]).filter(F.col("event_id") < n)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


# ------------------------------------------------------------- merge trees


def _tree(fan_in: int, agg: str = "min") -> Query:
    return lambda spark, sf_dir: tree_merge(_events(spark, sf_dir, 8192), "value", "event_id", 64, fan_in, agg)


def tree_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree_merge(_events(spark, sf_dir, 8192), "value", "event_id", 64, 8, "count").withColumnRenamed("value", "n")


def tree_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    cents = _events(spark, sf_dir, 8192).withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return tree_merge(cents, "cents", "event_id", 64, 8, "sum")


def tree_bit_or(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree_merge(_events(spark, sf_dir, 8192, "user_id"), "user_id", "event_id", 64, 8, "bit_or")


def tree_distinct_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct users by sketches merged along the tree: the estimate."""
    merged = tree_merge(_events(spark, sf_dir, 8192, "user_id"), "user_id", "event_id", 64, 8, "hll")
    return merged.select(F.hll_sketch_estimate("user_id").alias("users"))


def tree_min_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree_merge(_events(spark, sf_dir, 8192, "event_type", "value"), "value", "event_id", 64, 8, "min", ["event_type"])


def tree_partials_level1(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = tree_merge(_events(spark, sf_dir, 8192), "value", "event_id", 64, 8, "min", levels=True)
    return rows.filter("level = 1").select("idx", F.col("v").alias("least"))


def map_reduce_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Characters of all documents by map and tree merge."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return apps.map_reduce(docs, F.length("text").cast("long"), "doc_id", 64, 8).select(F.col("mapped").alias("chars"))


# ------------------------------------------------------------- cost models


def _values(spark: SparkSession, sf_dir: str, table: str = "events", column: str = "value") -> int:
    """Values of a column, counted by reading it."""
    return load(spark, sf_dir, table, [column]).agg(F.count(column)).first()[0]


def _busiest(spark: SparkSession, sf_dir: str, workers: int = 64) -> int:
    """Values of the worker that has most of all events' values."""
    loads = local_partials(assigned(load(spark, sf_dir, "events", ["event_id", "value"]), "event_id", workers), "value", "count")
    return loads.agg(F.max("v")).first()[0] or 0


def cost_tree_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of merging all events' values on 64 workers by fan-in; the busiest worker's scan counts."""
    return costmodel.tree_merge_table(spark, 64 * _busiest(spark, sf_dir), 64, [1, 2, 4, 8, 16, 32, 64], PUBLISHED_TREE)


def best_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Workers and fan-in that merge all events' values in the least modelled time."""
    return costmodel.best_tree(spark, _values(spark, sf_dir), PUBLISHED_TREE)


def cost_receive_send(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Receive and send time of nodes that get a user's events each, by message size."""
    loads = load(spark, sf_dir, "events", ["user_id"]).groupBy("user_id").agg(F.count("*").alias("messages"))
    return costmodel.receive_table(loads, SIMULATED)


def graph_shape(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Levels and tasks of the trees that merge all events on 64 workers."""
    partials = staged(local_partials(assigned(load(spark, sf_dir, "events", ["event_id", "value"]), "event_id", 64), "value"), "partials")
    return _union([costmodel.graph_shape(partials, 64, f).select(F.lit(f).alias("fan_in"), "level", "tasks") for f in (2, 4, 8, 16, 64)])


def cost_multicast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages of all line items' prices on 4,096 nodes with and without multicast, and the share that it saves."""
    keys = _values(spark, sf_dir, "lineitem", "l_extendedprice")
    totals = [messages.planned_ledger(spark, 4096, keys, (16, 16, 16), p).agg(F.sum("n_msgs").alias("n")).withColumn("multicast", F.lit(p.multicast)) for p in (SIMULATED, SIMULATED.with_(multicast=False))]
    both = _union(totals)
    return both.agg(F.max(F.when(F.col("multicast"), F.col("n"))).alias("multicast"), F.max(F.when(~F.col("multicast"), F.col("n"))).alias("unicast")).withColumn("saved", F.round(1 - F.col("multicast") / F.col("unicast"), 4))


def _clock_row(result, profile: NetworkProfile, **facts) -> DataFrame:
    row = costmodel.makespan(costmodel.simulate(result, profile))
    return row.select(*(F.lit(v).alias(k) for k, v in facts.items()), *row.columns)


def cost_tail_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of 256 nodes with 32 keys by the delay of 1 % of messages, for 16 and for 8 buckets (the text and the caption differ)."""
    parts = []
    for buckets, radices in ((16, (16, 16)), (8, (8, 8, 4))):
        result = recursive_sort(_events(spark, sf_dir, 8192), EVENT_KEY, SortConfig(256, fan_in=16, radices=radices))
        parts += [_clock_row(result, SIMULATED.with_(tail_ns=float(ns)), buckets=buckets, tail_ns=ns) for ns in (0, 1000, 2000, 4000)]
    return _union(parts)


def cost_switch_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time and idle time of 64 nodes with 16 keys by switching latency, for 8 and 4 buckets."""
    parts = []
    for b in (8, 4):
        result = recursive_sort(_events(spark, sf_dir, 1024), EVENT_KEY, SortConfig(64, b, 8))
        parts += [_clock_row(result, SIMULATED.with_(switch_ns=float(ns)), buckets=b, switch_ns=ns) for ns in (0, 100, 263, 500, 1000)]
    return _union(parts)


def _sized(spark: SparkSession, sf_dir: str, keys: int) -> DataFrame:
    """So many keys ``(k, rid)``: prices of line items, as many copies of the table as they need, the first by a hash of the copy and the
    row. Copies of a price differ in their record id alone."""
    lines = load(spark, sf_dir, "lineitem", [*LINE_ID, "l_extendedprice"])
    copies = max(1, -(-keys // max(1, lines.count())))
    spread = lines.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies)))).select(F.col("l_extendedprice").alias("price"), F.concat_ws(".", "l_extendedprice", *LINE_ID, "copy").alias("rid"))
    numbered = hash_row_number(spread.withColumn("h", fast_hash(F.col("rid"))), "h", ["rid", "price"], "at", max(8, keys // 50_000))
    return staged(numbered.filter(F.col("at") < keys).select("price", "rid"), "sized-keys")


def cost_multicast_clock(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of 131,072 keys on 4,096 nodes with and without multicast."""
    result = recursive_sort(_sized(spark, sf_dir, 131072), SIZED_KEY, SortConfig(4096, 16, 16, hash_name="fast"))
    return _union([_clock_row(result, SIMULATED.with_(multicast=m), multicast=m) for m in (True, False)])


def cost_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time and traffic by number of buckets a level: 4, 8 and 16 on 4,096 nodes."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).filter("o_orderkey < 131072")
    parts = []
    for b in (4, 8, 16):
        result = recursive_sort(orders, ORDER_KEY, SortConfig(4096, b, 16, hash_name="fast"))
        moved = messages.measured_ledger(result, SIMULATED).agg(F.sum("n_msgs").alias("n_msgs"), F.sum("n_bytes").alias("n_bytes"))
        parts.append(_clock_row(result, SIMULATED, buckets=b).crossJoin(F.broadcast(moved)))
    return _union(parts)


def cost_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time and skew of 4,096 nodes by number of keys: 16,384 (4 a node) to 262,144 (64 a node)."""
    parts = []
    for per_node in (4, 16, 64):
        result = recursive_sort(_sized(spark, sf_dir, 4096 * per_node), SIZED_KEY, SortConfig(4096, 16, 16, hash_name="fast"))
        parts.append(_clock_row(result, SIMULATED, per_node=per_node).crossJoin(F.broadcast(measures.skew(result.df, 4096).select("most", "skew"))))
    return _union(parts)


def skew_by_visibility(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Final skew of 4,096 nodes by keys a node, with capped samples and with full quantiles."""
    parts = []
    for per_node in (4, 16):
        keys = _sized(spark, sf_dir, 4096 * per_node)
        for policy in ("mixed", "full_quantile"):
            ranked = recursive_sort(keys, SIZED_KEY, SortConfig(4096, 16, 16, policy=policy, hash_name="fast")).df
            parts.append(measures.skew(ranked, 4096).withColumn("per_node", F.lit(per_node)).withColumn("policy", F.lit(policy)))
    return _union(parts)


def _flagship(spark: SparkSession, sf_dir: str):
    """All line items on 4,096 nodes (16 buckets, fan-in 16)."""
    line_id = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    lines = load(spark, sf_dir, "lineitem", [*line_id, "l_extendedprice"])
    return recursive_sort(lines, KeySpec.of("l_extendedprice", line_id), SortConfig(4096, 16, 16, hash_name="fast"))


def flagship_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    return costmodel.breakdown(staged(costmodel.simulate(_flagship(spark, sf_dir), SIMULATED), "clock"))


def flagship_throughput(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled records per millisecond and core."""
    result = _flagship(spark, sf_dir)
    keys = result.df.count()
    row = costmodel.makespan(costmodel.simulate(result, SIMULATED))
    return row.withColumn("records_per_ms_core", F.lit(float(keys)) / (F.col("sort_ns") / 1e6) / F.lit(4096))


def flagship_full(spark: SparkSession, sf_dir: str, seed: int = 7) -> DataFrame:
    """The published flagship: 1,048,576 keys on 65,536 nodes, 16 a node, 16 buckets and fan-in; modelled time, idle time and keys per
    millisecond and core. Minutes on one machine, so it is not among the registered queries; ``seed`` repeats it."""
    result = recursive_sort(_sized(spark, sf_dir, 1 << 20), SIZED_KEY, SortConfig(1 << 16, 16, 16, seed=seed, hash_name="fast"))
    row = costmodel.makespan(staged(costmodel.simulate(result, SIMULATED), "clock"))
    return row.withColumn("records_per_ms_core", F.lit(float(1 << 20)) / (F.col("sort_ns") / 1e6) / F.lit(1 << 16))


def idle_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    result = recursive_sort(_events(spark, sf_dir, 4096), EVENT_KEY, SortConfig(256, 4, 8))
    clock = staged(costmodel.simulate(result, SIMULATED), "clock")
    return costmodel.waits(clock).filter("wait_ns is not null").groupBy("level").agg(F.avg("wait_ns").alias("mean"), F.max("wait_ns").alias("most"))


def reorder_buffer(spark: SparkSession, sf_dir: str) -> DataFrame:
    result = recursive_sort(_events(spark, sf_dir, 4096), EVENT_KEY, SortConfig(256, 4, 8))
    clock = staged(costmodel.simulate(result, SIMULATED), "clock")
    return costmodel.reorder_depth(clock, messages.key_messages(result), SIMULATED)


#: The baseline sends its boundaries to every node one by one.
BASELINE_NET = SIMULATED.with_(multicast=False)


def _boundary_clock(keys: DataFrame, nodes: int, factor: int, per_node: int, facts: dict) -> DataFrame:
    placed, routed = baselines.boundary_run(keys, EVENT_KEY, nodes, factor, per_node)
    clock = costmodel.simulate_boundary_sort(placed, routed, nodes, factor, per_node, BASELINE_NET)
    last = depth(nodes, factor) + 1
    pivots = F.max(F.when(F.col("step") == last - 1, F.col("done_ns"))).alias("pivots_ns")
    return clock.agg(F.max("done_ns").alias("sort_ns"), pivots).select(*(F.lit(v).alias(k) for k, v in facts.items()), "sort_ns", "pivots_ns")


def bfs_cores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of the boundary-first sort by number of nodes, 16 keys a node, fan-in 4: boundaries grow with the nodes."""
    return _union([_boundary_clock(_events(spark, sf_dir, 16 * nodes), nodes, 4, 16, {"nodes": nodes, "keys": 16 * nodes}) for nodes in (64, 128, 256)])


def bfs_reduction_clock(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of the boundary-first sort of 4,096 keys on 128 nodes by reduction factor: each pivot sorter's load grows with it."""
    return _union([_boundary_clock(_events(spark, sf_dir, 4096), 128, factor, 32, {"reduction_factor": factor}) for factor in (2, 4, 8, 16, 32, 64)])


def rbs_against_bfs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled time of both sorts on the same keys, 16 a node, and the speed-up."""
    parts = []
    for nodes, radices in ((64, (8, 8)), (128, (8, 16)), (256, (16, 16))):
        keys = staged(_events(spark, sf_dir, 16 * nodes), "events")
        ours = _clock_row(recursive_sort(keys, EVENT_KEY, SortConfig(nodes, fan_in=8, radices=radices)), SIMULATED).select(F.col("sort_ns").alias("rbs_ns"))
        parts.append(_boundary_clock(keys, nodes, 4, 16, {"nodes": nodes}).select("nodes", F.col("sort_ns").alias("bfs_ns")).crossJoin(F.broadcast(ours)))
    return _union(parts).withColumn("speedup", F.col("bfs_ns") / F.col("rbs_ns"))


def median_tree_tuned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fan-in of the median tree with the least modelled latency, by nodes and hop."""
    rows = [(nodes, hop, best_fan_in(nodes, float(hop))) for nodes in (64, 256, 4096, 65536) for hop in (100, 349, 961)]
    return spark.createDataFrame(rows, "nodes int, hop_ns int, fan_in int")


def throughput_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.published(spark).select("system", "cores", "records_per_ms_core", "computed")


def repeated_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean, deviation and most of the modelled time over ten seeds (1,024 keys, 64 nodes)."""
    events = staged(_events(spark, sf_dir, 1024), "events")
    rows = [costmodel.makespan(costmodel.simulate(recursive_sort(events, EVENT_KEY, SortConfig(64, 8, 8, seed=s)), SIMULATED)).withColumn("seed", F.lit(s)) for s in range(10)]
    return _union(rows).agg(F.avg("sort_ns").alias("mean_ns"), F.stddev_samp("sort_ns").alias("std_ns"), F.max("sort_ns").alias("most_ns"), F.count("*").alias("runs"))


def distribution_independence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that end on another node when the key goes through a monotone function: none."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"])
    plain = recursive_sort(orders, ORDER_KEY, SortConfig(64, 8, 16)).df.select("o_orderkey", F.col("node").alias("a"), "rank")
    logged = recursive_sort(orders.withColumn("o_totalprice", F.log("o_totalprice")), ORDER_KEY, SortConfig(64, 8, 16)).df.select("o_orderkey", F.col("node").alias("b"), F.col("rank").alias("rank_b"))
    return plain.join(logged, "o_orderkey").agg(F.sum(F.when((F.col("a") != F.col("b")) | (F.col("rank") != F.col("rank_b")), 1).otherwise(0)).alias("moved"), F.count("*").alias("rows"))


def skew_by_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Final skew on near-unique, tied, dated, heavy-tailed and presorted keys."""
    line = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    cases = [("orders", "o_totalprice", ["o_orderkey"]), ("lineitem", "l_quantity", ["l_extendedprice", *line]), ("lineitem", "l_shipdate", ["l_extendedprice", *line]), ("events", "user_id", ["event_id"]), ("documents", "n_chars", ["doc_id"]), ("events", "event_id", ["event_id"])]
    parts = []
    for table, column, rid in cases:
        rows = load(spark, sf_dir, table, list(dict.fromkeys([column, *rid])))
        ranked = recursive_sort(rows, KeySpec.of(column, rid), SortConfig(64, 8, 16, hash_name="fast")).df
        parts.append(measures.skew(ranked, 64).withColumn("key", F.lit(f"{table}.{column}")))
    return _union(parts)


def expected_bucket_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected bucket sizes by policy, 8 buckets of 8 keys, and the two printed quantiles; ``keys``: so many of all events' values."""
    n = _values(spark, sf_dir)
    rows = [(p, i, x) for p in ("naive", "shifted", "mixed") for i, x in enumerate(expected_buckets(p, 8))]
    rows += [("smallest of 9", 0, median_quantile(9, [(1, 1.0)])), ("0.8 and 0.2 of 9", 0, median_quantile(9, [(1, 0.8), (2, 0.2)]))]
    share = F.when(F.col("policy").endswith("of 9"), F.col("size")).otherwise(F.col("size") / 8)
    return spark.createDataFrame(rows, "policy string, bucket int, size double").withColumn("keys", F.round(share * n, 3))


def pivot_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spread of the median pivot by number of nodes: halves when they are four times as many."""
    return measures.pivot_quantile_spread(spark, [16, 64, 256], 9, 5, 80)


# ------------------------------------------------------------- small tasks and applications


def min_scan_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One worker's least value over 64 to 8,192 values, with the modelled time."""
    return _union([baselines.single_scan_min(_events(spark, sf_dir, 2**i), "value").select(F.lit(2**i).alias("n"), F.col("value").alias("least"), F.lit(2**i * SIMULATED.scan_ns).alias("scan_ns")) for i in range(6, 14)])


def local_sort_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled local sort time by number of keys."""
    return spark.range(3, 11).select(F.pow(F.lit(2), F.col("id")).cast("int").alias("keys")).withColumn("sort_ns", costmodel.sort_ns(F.col("keys"), SIMULATED))


def local_sort_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local sorts of 8 to 1,024 keys, ten tasks of each size: what each sorted, and the modelled time."""
    runs = microtasks.sort_runs(load(spark, sf_dir, "events", ["event_id", "value"]), "value", "event_id", [2**i for i in range(3, 11)])
    n = F.size("keys")
    return runs.select("size", "run", n.alias("keys"), F.get("keys", F.lit(0)).alias("least"), F.get("keys", F.floor(n / 2).cast("int")).alias("mid"), F.get("keys", n - 1).alias("most"), costmodel.sort_ns(n, SIMULATED).alias("sort_ns"))


def local_sort_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]).filter("p_partkey < 2000")
    tasks = microtasks.local_sort(parts, "p_retailprice", "p_partkey", 40)
    return tasks.select("task", F.posexplode("keys").alias("at", "price"))


def scan_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    cents = load(spark, sf_dir, "events", ["event_id", "value"]).withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return microtasks.scan_words(cents, "cents", "event_id")


def loopback(spark: SparkSession, sf_dir: str) -> DataFrame:
    return microtasks.loopback(spark)


def kv_get_put(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every hundredth order gets a new status, then every fiftieth is read."""
    store = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderstatus"])
    updates = store.filter(F.col("o_orderkey") % 100 == 0).withColumn("o_orderstatus", F.lit("X"))
    requests = store.filter(F.col("o_orderkey") % 50 == 0).select("o_orderkey")
    return microtasks.kv_get(microtasks.kv_put(store, updates, "o_orderkey"), requests, "o_orderkey")


def set_intersect_postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return microtasks.intersect_sets(microtasks.word_ids(docs, "doc_id", "text"), ["the", "and", "license"])


def boolean_search_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return apps.boolean_search(docs, "doc_id", "text", ["the", "and"], ["license"], ["with", "from"])


def zorder_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    return apps.zorder_sort(vectors, "embedding", "vec_id", 3, SortConfig(16, 4, 4)).df.select("vec_id", "code", "rank")


def bounding_leaves(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    ranked = apps.zorder_sort(vectors, "embedding", "vec_id", 3, SortConfig(16, 4, 4)).df
    return apps.bounding_boxes(ranked, vectors, "vec_id", "embedding", 3, 16)


def median_tree_three_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A thousand nodes of nine keys, ten buckets, fan-in ten: medians of medians of medians of the i-th keys."""
    rows = _events(spark, sf_dir, 9000).select(F.lit(0).alias("grp"), F.floor(F.col("event_id") / 9).cast("int").alias("node"), F.struct("value", "event_id").alias("k"))
    local = rows.groupBy("grp", "node").agg(F.array_sort(F.collect_list("k")).alias("pivots"))
    return median_tree(local, 1000, 10).select(F.posexplode("pivots").alias("j", "p")).select("j", "p.value", "p.event_id")


def cost_host_stacks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best fan-in and modelled time of merging all events' values on 64 workers by the network's latency: lower latency makes deeper trees pay."""
    rows, values = [], 64 * _busiest(spark, sf_dir)
    for name, p in PRESETS.items():
        ns = {f: costmodel.tree_merge_ns(values, 64, f, p) for f in (2, 4, 8, 16, 32, 64)}
        best = min(ns, key=ns.get)
        rows.append((name, p.hop(64), best, round(ns[best], 3)))
    return spark.createDataFrame(rows, "profile string, hop_ns double, fan_in int, ns double")


def scan_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files and bytes below the tables that the workloads scan."""
    rows = [(t, *measures.scan_bytes(load(spark, sf_dir, t))) for t in ("events", "orders", "lineitem", "documents")]
    return spark.createDataFrame(rows, "table string, files int, bytes long")


def granularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The design rules as checks on the sorter's last level."""
    result = recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDER_KEY, SortConfig(64, 8, 16, policy="full_quantile"))
    report = measures.granularity_report(result.levels[-1].routed)
    return spark.createDataFrame([(report["single_partition"], report["row_python"], report["load"] < 3)], "single_partition boolean, row_python boolean, even boolean")


def udaf_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lower median element of each type's values by a grouped aggregate in Python, to check the expression form."""
    return _events(spark, sf_dir, 8192, "event_type", "value").groupBy("event_type").agg(median_element("value").alias("mid"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"tree_min_fanin_{f}": _tree(f) for f in (1, 2, 4, 8, 16, 32, 64)}
    out["tree_max"] = _tree(8, "max")
    for f in (
        tree_count, tree_sum, tree_bit_or, tree_distinct_sketch, tree_min_by_type, tree_partials_level1, map_reduce_length, cost_tree_merge, best_tree, cost_receive_send, graph_shape, cost_multicast, cost_tail_latency,
        cost_switch_latency, cost_multicast_clock, cost_buckets, cost_keys, skew_by_visibility, flagship_breakdown, flagship_throughput, idle_breakdown, reorder_buffer, bfs_cores, bfs_reduction_clock, rbs_against_bfs, median_tree_tuned, throughput_table, repeated_runs,
        distribution_independence, skew_by_distribution, expected_bucket_law, pivot_spread, min_scan_sizes, local_sort_sizes, local_sort_runs, local_sort_small, scan_words, loopback, kv_get_put, set_intersect_postings,
        boolean_search_documents, zorder_embeddings, bounding_leaves, median_tree_three_rounds, cost_host_stacks, scan_bytes, granularity, udaf_median,
    ):
        out[f.__name__] = f
    return out


def _bucket_law_sql() -> str:
    """Quantiles by bisection of the binomial sums, and the bucket sizes between them."""
    cdf = lambda n, i, q: f"list_sum(list_transform(range({i}, {n} + 1), lambda k: (factorial({n}::INT) / factorial(k::INT) / factorial(({n} - k)::INT))::DOUBLE * pow({q}, k) * pow(1 - {q}, {n} - k)))"
    mid = "(lo + hi) / 2"
    below = f"(w * {cdf('n', 'i', mid)} + (1 - w) * {cdf('n', '(i + 1)', mid)}) < 0.5"
    return f"""WITH RECURSIVE m(policy, j, n, i, w) AS (SELECT p, j, 8, j, (a * (8 - j) / 8.0 + l)::DOUBLE FROM (VALUES ('naive', 1.0, 0.0), ('shifted', 0.0, 0.5), ('mixed', 0.25, 0.375)) t(p, a, l), range(1, 8) r(j)
            UNION ALL VALUES ('smallest of 9', 1, 9, 1, 1.0::DOUBLE), ('0.8 and 0.2 of 9', 1, 9, 1, 0.8::DOUBLE)),
        b(policy, j, n, i, w, lo, hi, step) AS (SELECT *, 0.0::DOUBLE, 1.0::DOUBLE, 0 FROM m UNION ALL
            SELECT policy, j, n, i, w, CASE WHEN {below} THEN {mid} ELSE lo END, CASE WHEN {below} THEN hi ELSE {mid} END, step + 1 FROM b WHERE step < 60),
        q AS (SELECT policy, j, n, (lo + hi) / 2 AS q FROM b WHERE step = 60 UNION ALL SELECT DISTINCT policy, 0, 8, 0.0 FROM m WHERE n = 8)
        SELECT *, round(CASE WHEN policy LIKE '%of 9' THEN size ELSE size / 8 END * (SELECT count(value) FROM events), 3) AS keys FROM (
        SELECT policy, j::INT AS bucket, (coalesce(lead(q) OVER (PARTITION BY policy ORDER BY j), 1.0) - q) * 8 AS size FROM q WHERE n = 8 UNION ALL SELECT policy, 0, q FROM q WHERE n = 9)"""


def _morton_sql() -> str:
    cell = lambda i: f"greatest(0, least(255, floor((embedding[{i + 1}]::DOUBLE + 4.0) / 8.0 * 256)))::BIGINT"
    bits = " + ".join(f"(((c{d} >> {bit}) & 1) << {bit * 3 + d})" for bit in range(8) for d in range(3))
    return f"SELECT vec_id, {bits} AS code FROM (SELECT vec_id, {', '.join(f'{cell(i)} AS c{i}' for i in range(3))} FROM embeddings)"


def _median_round(t: int) -> str:
    over = "PARTITION BY j, idx // 10"
    upper = f"CASE WHEN (idx // 10 + {t}) % 2 = 1 THEN count(*) OVER ({over}) // 2 + 1 ELSE (count(*) OVER ({over}) - 1) // 2 + 1 END"
    return f"t{t} AS (SELECT j, idx // 10 AS idx, value, event_id FROM t{t - 1} QUALIFY row_number() OVER ({over} ORDER BY value, event_id) = {upper})"


def _words_sql() -> str:
    return "SELECT doc_id AS id, list_distinct(list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '')) AS w FROM documents"


def oracle_sql() -> dict[str, str]:
    e = "events WHERE event_id < 8192"
    out = {f"tree_min_fanin_{f}": f"SELECT min(value) AS value FROM {e}" for f in (1, 2, 4, 8, 16, 32, 64)}
    morton = _morton_sql()
    out |= {
        "tree_max": f"SELECT max(value) AS value FROM {e}",
        "tree_count": f"SELECT count(*) AS n FROM {e}",
        "tree_sum": f"SELECT sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM {e}",
        "tree_bit_or": f"SELECT bit_or(user_id) AS user_id FROM {e}",
        "tree_min_by_type": f"SELECT event_type, min(value) AS value FROM {e} GROUP BY 1",
        "tree_partials_level1": f"SELECT ((event_id % 64) // 8)::INT AS idx, min(value) AS least FROM {e} GROUP BY 1",
        "map_reduce_length": "SELECT sum(length(text))::BIGINT AS chars FROM documents",
        "cost_tree_merge": """WITH RECURSIVE f(fan_in) AS (VALUES (2), (4), (8), (16), (32), (64)),
            l(fan_in, left_, depth, ns) AS (SELECT fan_in, 64, 0, (SELECT max(n) FROM (SELECT count(value) AS n FROM events GROUP BY event_id % 64)) * 2.2::DOUBLE FROM f UNION ALL
              SELECT fan_in, ceil(left_ / fan_in)::INT, depth + 1, ns + 185 + 8 + (least(fan_in, left_) - 1) * 6.22::DOUBLE FROM l WHERE left_ > 1)
            SELECT fan_in, depth, round(ns, 3) AS ns FROM l WHERE left_ = 1 UNION ALL SELECT 1, 63, round((SELECT max(n) FROM (SELECT count(value) AS n FROM events GROUP BY event_id % 64)) * 2.2::DOUBLE + 63 * 193, 3)""",
        "best_tree": """WITH RECURSIVE g(workers, fan_in) AS (SELECT pow(2, i)::INT, f FROM range(11) a(i), (VALUES (1), (2), (4), (8), (16), (32), (64)) b(f) WHERE f <= greatest(1, pow(2, i))),
            l(workers, fan_in, left_, ns) AS (SELECT workers, fan_in, CASE WHEN fan_in = 1 THEN 1 ELSE workers END, (SELECT count(value) FROM events)::DOUBLE / workers * 2.2::DOUBLE + CASE WHEN fan_in = 1 THEN (workers - 1) * 193.0::DOUBLE ELSE 0 END FROM g UNION ALL
              SELECT workers, fan_in, ceil(left_ / fan_in)::INT, ns + 185 + 8 + (least(fan_in, left_) - 1) * 6.22::DOUBLE FROM l WHERE left_ > 1)
            SELECT workers, fan_in, round(ns, 3) AS ns FROM l WHERE left_ = 1 ORDER BY ns LIMIT 1""",
        "cost_host_stacks": """WITH RECURSIVE p(profile, hop_ns) AS (VALUES ('simulated', 349.0::DOUBLE), ('tree_merge_published', 185.0::DOUBLE), ('software_stack', 850.0::DOUBLE), ('integrated_nic', 100.0::DOUBLE), ('register_nic', 69.0::DOUBLE)),
            l(profile, hop_ns, fan_in, left_, ns) AS (SELECT profile, hop_ns, f, 64, (SELECT max(n) FROM (SELECT count(value) AS n FROM events GROUP BY event_id % 64)) * 2.2::DOUBLE FROM p, (VALUES (2), (4), (8), (16), (32), (64)) b(f) UNION ALL
              SELECT profile, hop_ns, fan_in, ceil(left_ / fan_in)::INT, ns + hop_ns + 8 + (least(fan_in, left_) - 1) * 6.22::DOUBLE FROM l WHERE left_ > 1)
            SELECT profile, hop_ns, fan_in, round(ns, 3) AS ns FROM l WHERE left_ = 1 QUALIFY row_number() OVER (PARTITION BY profile ORDER BY ns, fan_in) = 1""",
        "median_tree_tuned": """WITH RECURSIVE g(nodes, hop_ns, fan_in) AS (SELECT n, h, f FROM (VALUES (64), (256), (4096), (65536)) a(n), (VALUES (100), (349), (961)) b(h), range(2, 65) c(f)),
            l(nodes, hop_ns, fan_in, left_, levels) AS (SELECT *, nodes, 0 FROM g UNION ALL SELECT nodes, hop_ns, fan_in, ceil(left_ / fan_in)::INT, levels + 1 FROM l WHERE left_ > 1)
            SELECT nodes, hop_ns, fan_in::INT AS fan_in FROM l WHERE left_ = 1 QUALIFY row_number() OVER (PARTITION BY nodes, hop_ns ORDER BY levels * (hop_ns + 8 + (least(fan_in, nodes) - 1) * 6.22::DOUBLE), fan_in) = 1""",
        "expected_bucket_law": _bucket_law_sql(),
        "cost_receive_send": """SELECT m AS messages, b AS bytes, count(*) AS nodes, greatest(8.0::DOUBLE + (m - 1) * 6.22::DOUBLE, m * b * 8.0::DOUBLE / 200) AS receive_ns, greatest(m * 4.0::DOUBLE, m * b * 8.0::DOUBLE / 200) AS send_ns
            FROM (SELECT count(*) AS m FROM events GROUP BY user_id), (VALUES (16), (32), (64), (128), (256)) v(b) GROUP BY m, b""",
        "graph_shape": "SELECT f AS fan_in, l::INT AS level, count(DISTINCT (event_id % 64) // pow(f, l)::INT) AS tasks FROM events, (VALUES (2, 6), (4, 3), (8, 2), (16, 2), (64, 1)) v(f, d), range(7) t(l) WHERE l <= d GROUP BY 1, 2",
        "cost_multicast": """WITH k AS (SELECT count(l_extendedprice) AS n, 15 * 4096 * 3 AS up FROM lineitem), t AS (SELECT n * 5 + up + 15 * (1 + 16 + 256) AS multicast, n * 5 + 2 * up AS unicast FROM k)
            SELECT multicast, unicast, round(1 - multicast / unicast, 4) AS saved FROM t""",
        "median_tree_three_rounds": f"""WITH t0 AS (SELECT row_number() OVER (PARTITION BY event_id // 9 ORDER BY value, event_id) - 1 AS j, event_id // 9 AS idx, value, event_id FROM events WHERE event_id < 9000),
            {", ".join(_median_round(t) for t in (1, 2, 3))}
            SELECT (row_number() OVER (ORDER BY value, event_id) - 1)::INT AS j, value, event_id FROM t3""",
        "granularity": "SELECT false AS single_partition, false AS row_python, true AS even",
        "udaf_median": "SELECT event_type, quantile_disc(value, 0.5) AS mid FROM events WHERE event_id < 8192 GROUP BY 1",
        "throughput_table": """SELECT * FROM (VALUES ('recursive bucket sort', 65536, 224, 224.4), ('boundary-first sort', 2240, 1297, 446.4), ('record-holding cluster sort', 10240, 1977, NULL), ('in-memory cluster sort', 3072, 707, NULL)) t(system, cores, records_per_ms_core, computed)""",
        "distribution_independence": "SELECT 0 AS moved, count(*) AS rows FROM orders",
        "min_scan_sizes": "SELECT pow(2, i)::INT AS n, (SELECT min(value) FROM events WHERE event_id < pow(2, i)) AS least, pow(2, i) * 2.2::DOUBLE AS scan_ns FROM range(6, 14) t(i)",
        "local_sort_sizes": "SELECT pow(2, i)::INT AS keys, 2.93::DOUBLE * pow(2, i) * log2(pow(2, i)) AS sort_ns FROM range(3, 11) t(i)",
        "local_sort_runs": """WITH r AS (SELECT s AS size, (event_id // s)::INT AS run, value, row_number() OVER (PARTITION BY s, event_id // s ORDER BY value) - 1 AS at_, count(*) OVER (PARTITION BY s, event_id // s) AS n
            FROM events, (VALUES (8), (16), (32), (64), (128), (256), (512), (1024)) v(s) WHERE event_id // s < 10)
            SELECT size, run, max(n)::INT AS keys, min(value) AS least, max(value) FILTER (WHERE at_ = n // 2) AS mid, max(value) AS most, CASE WHEN max(n) > 1 THEN 2.93::DOUBLE * max(n) * log2(max(n)) ELSE 0.0 END AS sort_ns FROM r GROUP BY size, run""",
        "local_sort_small": "SELECT p_partkey // 40 AS task, (row_number() OVER (PARTITION BY p_partkey // 40 ORDER BY p_retailprice) - 1)::INT AS at, p_retailprice AS price FROM part WHERE p_partkey < 2000".replace(" AS at", ' AS "at"'),
        "scan_words": "SELECT event_id // 1024 AS task, sum(round(value * 100)::BIGINT)::BIGINT AS total, min(round(value * 100)::BIGINT) AS least, count(*) AS n FROM events GROUP BY 1",
        "loopback": "SELECT i::INT AS src, i::INT AS dst, 118 AS n_msgs, 16 * 118 AS n_bytes FROM range(64) t(i)",
        "kv_get_put": "SELECT o_orderkey, CASE WHEN o_orderkey % 100 = 0 THEN 'X' ELSE o_orderstatus END AS o_orderstatus FROM orders WHERE o_orderkey % 50 = 0",
        "set_intersect_postings": f"SELECT id FROM ({_words_sql()}) WHERE list_contains(w, 'the') AND list_contains(w, 'and') AND list_contains(w, 'license')",
        "boolean_search_documents": f"SELECT id FROM ({_words_sql()}) WHERE list_contains(w, 'the') AND list_contains(w, 'and') AND NOT list_contains(w, 'license') AND (list_contains(w, 'with') OR list_contains(w, 'from'))",
        "zorder_embeddings": f"SELECT vec_id, code, row_number() OVER (ORDER BY code, vec_id) - 1 AS rank FROM ({morton})",
        "bounding_leaves": f"""WITH r AS (SELECT vec_id, (row_number() OVER (ORDER BY code, vec_id) - 1) // 16 AS leaf FROM ({morton}))
            SELECT leaf, count(*) AS n, {', '.join(f'min(embedding[{i + 1}]) AS lo{i}, max(embedding[{i + 1}]) AS hi{i}' for i in range(3))} FROM r JOIN embeddings USING (vec_id) GROUP BY leaf""",
    }
    return out


