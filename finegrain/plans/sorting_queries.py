"""Registered queries of the sorter, its stages, variants and baselines."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain.functions.hashing import portable_hash
from finegrain.functions.keys import KeySpec
from finegrain.functions.pivots import POLICIES, case_between, case_double, case_equal, case_short, pick_pivots
from finegrain.operators import baselines, mediantree, payload, placement
from finegrain.operators.sorter import SortConfig, attach_pivots, first_pivots, global_rank, keyed_rows, local_sample, ranks_of, recursive_sort, select_rank, top_k
from finegrain.plans import measures, messages
from finegrain.plans.profile import PRESETS
from finegrain.sources.staging import fresh_path, staged
from finegrain.sources.tables import load

Query = Callable[[SparkSession, str], DataFrame]

ORDERS, EVENTS = KeySpec.of("o_totalprice", "o_orderkey"), KeySpec.of("value", "event_id")
LINE_ID = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
SMALL = SortConfig(64, 8, 16)


def _ranks(table: str, key: KeySpec, cfg: SortConfig, *columns: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        wanted = dict.fromkeys([*(c.lstrip("-") for c in key.order), *key.rid, *columns])
        ranked = recursive_sort(load(spark, sf_dir, table, list(wanted)), key, cfg).df
        return ranked.select(*wanted, "rank")

    return query


def rbs_rank_events_ts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by time."""
    ranked = recursive_sort(load(spark, sf_dir, "events", ["event_id", "ts"]), KeySpec.of("ts", "event_id"), SMALL).df
    return ranked.select("event_id", "rank")


def rbs_payload_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys are sorted alone; the texts join them at the end."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "n_chars", "lang", "text"])
    key = KeySpec.of("n_chars", "doc_id")
    ranked = recursive_sort(docs.select("doc_id", "n_chars"), key, SMALL).df.select("doc_id", "n_chars", "rank")
    full = payload.redistribute(ranked, docs, key)
    return full.select("doc_id", "rank", "lang", F.md5(F.encode("text", "UTF-8")).alias("text_md5"))


def rbs_initial_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "orders", ["o_orderkey"]).withColumn("_rid", F.col("o_orderkey").cast("string"))
    return placement.initial_shuffle(rows, 64, 7).select("o_orderkey", "node")


def _level(spark: SparkSession, sf_dir: str, cfg: SortConfig, level: int):
    return recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, cfg).levels[level]


def rbs_level0_local_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    local = _level(spark, sf_dir, SMALL, 0).local
    return local.select("node", F.posexplode("pivots").alias("j", "p")).select("node", "j", F.col("p.c0_0").alias("price"), F.col("p.r0").alias("id"))


def rbs_level0_median_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _level(spark, sf_dir, SMALL, 0).pivots
    return rows.select("grp", F.posexplode("pivots").alias("j", "p")).select("grp", "j", F.col("p.c0_0").alias("price"), F.col("p.r0").alias("id"))


def rbs_level0_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _level(spark, sf_dir, SMALL, 0).routed.select("o_orderkey", "bucket", "node")


def rbs_level1_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _level(spark, sf_dir, SMALL, 1).routed.select("o_orderkey", "bucket", "node")


def rbs_final_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _level(spark, sf_dir, SortConfig(16, 16, 16), 0).routed.groupBy("node").agg(F.count("*").alias("n"))


#: Policies by name; the two-point mixture is the published one.
ALL_POLICIES = {**{p: p for p in POLICIES}, "calibrated": "calibrated", "two_point": ("mix", (0.8, 0.2))}


def rbs_skew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Final skew by pivot policy where it matters: about as many keys a node as buckets (1,000 nodes of ten keys at sf0.01)."""
    out = None
    events = load(spark, sf_dir, "events", ["event_id", "value"])
    nodes = 10 ** max(1, round(math.log10(max(events.count(), 1))) - 1)
    for name, policy in (*ALL_POLICIES.items(), ("full_quantile", "full_quantile")):
        ranked = recursive_sort(events, EVENTS, SortConfig(nodes, 10, 10, policy=policy)).df
        row = measures.skew(ranked, nodes).withColumn("policy", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def _ten_a_node(spark: SparkSession, sf_dir: str):
    """Events on a tenth as many nodes, ten keys each, in hash order: ``(node, sample)``, and all keys ``k``."""
    keys = keyed_rows(load(spark, sf_dir, "events", ["event_id", "value"]), EVENTS)
    nodes = max(1, keys.count() // 10)
    placed = staged(placement.initial_shuffle(keys, nodes, 7), "placed")
    cfg = SortConfig(nodes, radices=(nodes,)) if nodes > 1 else SortConfig(1)
    sample = local_sample(placed.withColumn("grp", F.lit(0)), 0, cfg, 10)
    return placed, staged(sample, "samples"), nodes


def _policy_pivots(sample: DataFrame, nodes: int, policy) -> DataFrame:
    draw = lambda purpose, *more: portable_hash(7, 0, purpose, F.col("node"), *more)
    local = sample.select("grp", "node", pick_pivots(F.col("keys"), 10, draw, policy).alias("pivots"))
    return mediantree.median_tree(local, nodes, 10)


def policy_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nine pivots of all events by policy, from nodes of ten keys and trees of medians with fan-in ten."""
    _, sample, nodes = _ten_a_node(spark, sf_dir)
    parts = [_policy_pivots(sample, nodes, policy).select(F.lit(name).alias("policy"), F.posexplode("pivots").alias("j", "p")) for name, policy in ALL_POLICIES.items()]
    return reduce(DataFrame.unionByName, parts).select("policy", "j", F.col("p.c0_0").alias("value"), F.col("p.r0").alias("event_id"))


def policy_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in each of the ten buckets that a policy's pivots make."""
    placed, sample, nodes = _ten_a_node(spark, sf_dir)
    parts = []
    for name, policy in ALL_POLICIES.items():
        cuts = staged(_policy_pivots(sample, nodes, policy), "policy-pivots")
        bucketed = attach_pivots(placed.withColumn("grp", F.lit(0)), cuts, 1).select(placement.bucket_of("k", "pivots", 9).alias("bucket"))
        parts.append(bucketed.groupBy("bucket").agg(F.count("*").alias("n")).withColumn("policy", F.lit(name)))
    return reduce(DataFrame.unionByName, parts)


def rbs_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    keys = load(spark, sf_dir, "orders", ["o_orderkey"]).count()
    return messages.planned_ledger(spark, 64, keys, (8, 8), PRESETS["simulated"])


def rbs_messages_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    result = recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, SMALL)
    return messages.measured_ledger(result, PRESETS["simulated"])


def rbs_traffic_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return messages.traffic(rbs_messages(spark, sf_dir))


def rbs_group_isolation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Key messages that leave their group, by level: none."""
    result = recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, SMALL)
    moved = messages.key_messages(result)
    width = F.when(F.col("level") == 0, 64).otherwise(8)
    return moved.groupBy("level").agg(F.sum(F.when(F.floor(F.col("src") / width) != F.floor(F.col("dst") / width), F.col("n_msgs")).otherwise(0)).alias("leaving"), F.sum("n_msgs").alias("n_msgs"))


def rbs_verify(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.verify_sorted(recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, SMALL).df)


def rbs_node_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    result = recursive_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, SMALL)
    return messages.node_load(messages.key_messages(result))


# ------------------------------------------------------------- baselines


def bfs_rank_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load(spark, sf_dir, "events", ["event_id", "value"]).filter("event_id < 4096")
    return baselines.boundary_sort(events, KeySpec.of("value", "event_id"), 256, 4).select("event_id", "value", "rank")


def bfs_reduction_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skew and pivot-sorter levels of the boundary-first sort by reduction factor."""
    events = load(spark, sf_dir, "events", ["event_id", "value"]).filter("event_id < 4096")
    out = None
    for factor in (2, 4, 8, 16):
        ranked = baselines.boundary_sort(events, KeySpec.of("value", "event_id"), 128, factor)
        row = measures.skew(ranked, 128).withColumn("reduction_factor", F.lit(factor))
        out = row if out is None else out.unionByName(row)
    return out


def bfs_boundaries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The root's boundaries of 64 buckets from 64 nodes, one round of pivot sorters."""
    events = load(spark, sf_dir, "events", ["event_id", "value"]).filter("event_id < 4096")
    placed = placement.initial_shuffle(keyed_rows(events, KeySpec.of("value", "event_id")), 64, 7)
    cuts = baselines.boundaries(placed, 64, 64, 8)
    return cuts.select(F.posexplode("pivots").alias("j", "p")).select("j", F.col("p.c0_0").alias("value"), F.col("p.r0").alias("event_id"))


def builtin_sort_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spark's range-partitioned sort; ranks by partition offsets as for the other sorts."""
    orders = baselines.builtin_sort(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), "o_totalprice", "o_orderkey")
    placed = orders.withColumn("node", F.spark_partition_id()).withColumn("k", F.struct("o_totalprice", "o_orderkey"))
    return global_rank(staged(placed, "ranges"), 4096).select("o_orderkey", "o_totalprice", "rank")


def single_sort_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]).filter("p_partkey < 1024")
    return baselines.single_sort(parts, "p_retailprice", "p_partkey")


def single_scan_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.single_scan_min(load(spark, sf_dir, "events", ["event_id", "value"]).filter("event_id < 8192"), "value")


def global_random_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = baselines.global_random_pivots(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ORDERS, 16)
    return drawn.select("j", "o_orderkey", "o_totalprice")


def proportional_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes for each of 16 equal ranges of the price by its number of orders."""
    counts = load(spark, sf_dir, "orders", ["o_totalprice"]).groupBy(F.floor(F.col("o_totalprice") / 40000).cast("int").alias("bucket")).agg(F.count("*").alias("n"))
    return placement.proportional(counts, 64)


# ------------------------------------------------------------- pivots


def _nodes_of(spark: SparkSession, sf_dir: str, size: int) -> DataFrame:
    """``(node, sample)``: events by id, ``size`` to a node, in hash order."""
    events = load(spark, sf_dir, "events", ["event_id", "value"]).filter(F.col("event_id") < size * 100)
    h = portable_hash(7, 0, "pick", F.col("event_id"))
    rows = events.select(F.floor(F.col("event_id") / size).cast("int").alias("node"), F.struct(h.alias("h"), F.col("event_id").cast("string").alias("r"), F.struct("value", "event_id").alias("k")).alias("x"))
    return rows.groupBy("node").agg(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["k"]).alias("sample"))


def _pivot_query(size: int, b: int, make, policy: str = "mixed") -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        draw = lambda purpose, *more: portable_hash(7, 0, purpose, F.col("node"), *more)
        picked = _nodes_of(spark, sf_dir, size).select("node", F.posexplode(make(F.slice("sample", 1, 2 * b), b, draw, policy)).alias("j", "p"))
        return picked.select("node", "j", "p.value", "p.event_id")

    return query


def exact_median_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact lower medians over 100 nodes of 8 keys, naive picks."""
    draw = lambda purpose, *more: portable_hash(7, 0, purpose, F.col("node"), *more)
    local = _nodes_of(spark, sf_dir, 8).select(F.lit(0).alias("grp"), "node", case_equal(F.col("sample"), 8, draw, "naive").alias("pivots"))
    return mediantree.exact_median(local).select(F.posexplode("pivots").alias("j", "p")).select("j", "p.value", "p.event_id")


def median_tree_vs_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank distance, among all keys, of the tree's pivots from the exact medians."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"])
    n = orders.count()
    local, pivots = first_pivots(orders, ORDERS, SortConfig(64, 64, 4, policy="full_quantile"))
    made = {"tree_q": pivots, "exact_q": staged(mediantree.exact_median(local), "exact-pivots")}
    picked = {name: rows.select(F.posexplode("pivots").alias("j", "k")) for name, rows in made.items()}
    ranks = ranks_of(orders, ORDERS, picked["tree_q"].unionByName(picked["exact_q"])).select("k", (F.col("rank") / F.lit(max(n - 1, 1))).alias("q"))
    tree, exact = (rows.join(F.broadcast(ranks), "k").select("j", F.col("q").alias(name)) for name, rows in picked.items())
    return tree.join(exact, "j").withColumn("distance", F.abs(F.col("tree_q") - F.col("exact_q")))


def quantile_smallest_of_9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.pivot_quantile_spread(spark, [25, 100, 400], 9, 1, 60)


# ------------------------------------------------------------- selection


def top_k_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", [*LINE_ID, "l_extendedprice"])
    return top_k(lines, KeySpec.of("l_extendedprice", LINE_ID), 100, SMALL).select(*LINE_ID, "l_extendedprice", "rank")


def select_rank_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", [*LINE_ID, "l_extendedprice"])
    return select_rank(lines, KeySpec.of("l_extendedprice", LINE_ID), 1234, SMALL).select(*LINE_ID, "l_extendedprice", "rank")


def global_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact elements at every tenth of the order, from ranks."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"])
    n = orders.count()
    ranked = recursive_sort(orders, ORDERS, SMALL).df
    return ranked.filter(F.col("rank").isin([q * n // 10 for q in range(10)])).select("rank", "o_orderkey", "o_totalprice")


def range_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A price range read back from sorted files."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"])
    ranked = recursive_sort(orders, ORDERS, SMALL).df.select("o_orderkey", "o_totalprice", "rank", "k")
    path = fresh_path(spark, "sorted")
    payload.write_sorted(ranked, path, 4000, ["o_totalprice", "o_orderkey"])
    return payload.range_lookup(spark, f"{path}/keys", "o_totalprice", 100000.0, 120000.0).select("o_orderkey", "o_totalprice", "rank")


def sql_functions_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bucket and node through the SQL functions."""
    from finegrain.functions.udfs import register

    register(spark)
    load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).createOrReplaceTempView("fg_orders")
    return spark.sql(
        """SELECT o_orderkey, fg_bucket(o_totalprice, array(50000D, 100000D, 150000D)) AS bucket,
                  fg_node(0, 64, 4, fg_bucket(o_totalprice, array(50000D, 100000D, 150000D)), fg_hash(concat('7|0|route|', o_orderkey))) AS node
           FROM fg_orders"""
    )


def udtf_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Evenly spaced pivots of each node by the table function."""
    from finegrain.functions.udfs import register

    register(spark)
    load(spark, sf_dir, "events", ["event_id", "value"]).filter("event_id < 640").selectExpr("cast(event_id div 64 as int) AS node", "value AS k").createOrReplaceTempView("fg_keys")
    rows = spark.sql("SELECT * FROM fg_pivots(4, TABLE(SELECT node, k FROM fg_keys) PARTITION BY node)")
    return rows.select("node", "n", F.posexplode("pivots").alias("j", "pivot"))


def queries() -> dict[str, Query]:
    orders = lambda cfg: _ranks("orders", ORDERS, cfg)
    out: dict[str, Query] = {
        "rbs_rank_orders": orders(SMALL),
        "rbs_rank_lineitem_price": _ranks("lineitem", KeySpec.of("l_extendedprice", LINE_ID), SortConfig(4096, 16, 16)),
        "rbs_rank_lineitem_quantity_ties": _ranks("lineitem", KeySpec.of("l_quantity", ["l_extendedprice", *LINE_ID]), SortConfig(256, 16, 16)),
        "rbs_rank_events_value_desc": _ranks("events", KeySpec.of("-value", "event_id"), SMALL),
        "rbs_rank_events_ts": rbs_rank_events_ts,
        "rbs_rank_documents_nchars": _ranks("documents", KeySpec.of("n_chars", "doc_id"), SortConfig(16, 4, 4)),
        "rbs_rank_customer_multi_key": _ranks("customer", KeySpec.of(["c_mktsegment", "-c_acctbal"], "c_custkey"), SortConfig(16, 4, 4)),
        "rbs_rank_part_name_desc": _ranks("part", KeySpec.of(["-p_name"], "p_partkey"), SortConfig(16, 4, 4)),
        "rbs_rank_pages_url": _ranks("pages", KeySpec.of("url", "page_id"), SortConfig(8, 2, 2)),
        "rbs_rank_conversations": _ranks("conversations", KeySpec.of(["conv_id", "turn"], ["conv_id", "turn"]), SortConfig(16, 4, 4)),
        "rbs_naive": orders(SortConfig(64, 8, 16, policy="naive")),
        "rbs_shifted": orders(SortConfig(64, 8, 16, policy="shifted")),
        "rbs_full_quantile": orders(SortConfig(64, 8, 16, policy="full_quantile")),
        "rbs_calibrated": orders(SortConfig(64, 8, 16, policy="calibrated")),
        "rbs_exact_median": orders(SortConfig(64, 8, 16, median="exact")),
        "rbs_truncated_tree": orders(SortConfig(64, 8, 4, participants=16)),
        "rbs_lower_median_rule": orders(SortConfig(64, 8, 4, rule="lower")),
        "rbs_mixed_radix": orders(SortConfig(96, radices=(8, 4, 3))),
        "rbs_adaptive_stop": orders(SortConfig(64, 8, 16, target_rows=1900)),
        "rbs_hash_placement": orders(SortConfig(64, 8, 16, initial="hash", hash_name="fast")),
        "rbs_physical": orders(SortConfig(64, 8, 16, mode="physical", initial="hash", hash_name="fast")),
        "rbs_fused": orders(SortConfig(64, 64, 16, mode="fused")),
        "rbs_carry_record": _ranks("orders", ORDERS, SortConfig(64, 8, 16, carry="record"), "o_custkey", "o_orderpriority"),
        "pivots_naive": _pivot_query(8, 8, case_equal, "naive"),
        "pivots_shifted": _pivot_query(8, 8, case_equal, "shifted"),
        "pivots_mixed": _pivot_query(8, 8, case_equal, "mixed"),
        "pivots_case_equal": _pivot_query(16, 16, case_equal),
        "pivots_case_short": _pivot_query(5, 8, case_short),
        "pivots_case_between": _pivot_query(12, 8, case_between),
        "pivots_case_double": _pivot_query(16, 8, case_double),
        "pivots_case_long": _pivot_query(40, 8, case_double),
    }
    for f in (
        rbs_payload_documents, rbs_initial_shuffle, rbs_level0_local_pivots, rbs_level0_median_tree, rbs_level0_route, rbs_level1_route, rbs_final_counts, rbs_skew, rbs_messages,
        rbs_messages_measured, rbs_traffic_cube, rbs_group_isolation, rbs_verify, rbs_node_load, bfs_rank_events, bfs_reduction_sweep, bfs_boundaries, builtin_sort_orders, single_sort_part, single_scan_min,
        policy_pivots, policy_buckets, global_random_pivots, proportional_nodes, exact_median_pivots, median_tree_vs_exact, quantile_smallest_of_9, top_k_lineitem, select_rank_lineitem, global_quantiles, range_lookup, sql_functions_route, udtf_pivots,
    ):
        out[f.__name__] = f
    return out


