"""Whole-table forms of the queries that run at an experiment's published size on a prefix of the ids; ``<name>_whole`` of each.

Numbers of workers and nodes come from the table's rows: 128 values a worker of a merge tree and 64 keys a node, as in the
experiments, so the work of one worker stays as it is when the table grows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain.functions.hashing import portable_hash
from finegrain.functions.keys import KeySpec
from finegrain.functions.pivots import pick_pivots
from finegrain.functions.udfs import median_element
from finegrain.operators import baselines, mediantree, microtasks, placement
from finegrain.operators.sorter import SortConfig, keyed_rows
from finegrain.operators.treemerge import tree_merge
from finegrain.plans import measures
from finegrain.plans.sorting_oracles import MIXED, NAIVE, SHIFTED, digest
from finegrain.sources.staging import fresh_path, staged
from finegrain.sources.tables import load
from finegrain.streaming import merges

Query = Callable[[SparkSession, str], DataFrame]

EVENT_KEY = KeySpec.of("value", "event_id")
PER_WORKER, PER_NODE = 128, 64


def _events(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return load(spark, sf_dir, "events", ["event_id", *(columns or ("value",))])


def _share(rows: DataFrame, each: int) -> int:
    """Workers for all ``rows`` at ``each`` rows a worker."""
    return max(1, -(-rows.count() // each))


# ------------------------------------------------------------- merge trees


def _merged(rows: DataFrame, value: str, fan_in: int = 8, agg: str = "min", *more, **options) -> DataFrame:
    return tree_merge(rows, value, "event_id", _share(rows, PER_WORKER), fan_in, agg, *more, **options)


def _tree(fan_in: int, agg: str = "min") -> Query:
    return lambda spark, sf_dir: _merged(_events(spark, sf_dir), "value", fan_in, agg)


def tree_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir), "value", 8, "count").withColumnRenamed("value", "n")


def tree_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir).withColumn("cents", F.round(F.col("value") * 100).cast("long")), "cents", 8, "sum")


def tree_bit_or(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir, "user_id"), "user_id", 8, "bit_or")


def tree_distinct_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir, "user_id"), "user_id", 8, "hll").select(F.hll_sketch_estimate("user_id").alias("users"))


def tree_min_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir, "event_type", "value"), "value", 8, "min", ["event_type"])


def tree_partials_level1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _merged(_events(spark, sf_dir), "value", levels=True).filter("level = 1").select("idx", F.col("v").alias("least"))


def udaf_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, "event_type", "value").groupBy("event_type").agg(median_element("value").alias("mid"))


def local_sort_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    tasks = microtasks.local_sort(load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", "p_partkey", 40)
    return tasks.select("task", F.posexplode("keys").alias("at", "price"))


# ------------------------------------------------------------- baselines and pivots


def bfs_rank_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = _events(spark, sf_dir)
    return baselines.boundary_sort(events, EVENT_KEY, _share(events, PER_NODE), 4).select("event_id", "value", "rank")


def bfs_reduction_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    events, out = _events(spark, sf_dir), None
    nodes = _share(events, PER_NODE)
    placed = baselines.placed_keys(events, EVENT_KEY, nodes)
    for factor in (2, 4, 8, 16):
        row = measures.skew(baselines.routed_by_boundaries(placed, nodes, factor), nodes).withColumn("reduction_factor", F.lit(factor)).withColumn("nodes", F.lit(nodes))
        out = row if out is None else out.unionByName(row)
    return out


def bfs_boundaries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The root's boundaries of as many buckets as nodes, one round of pivot sorters."""
    events = _events(spark, sf_dir)
    nodes = _share(events, PER_NODE)
    cuts = baselines.boundaries(placement.initial_shuffle(keyed_rows(events, EVENT_KEY), nodes, 7), nodes, nodes, 8)
    return staged(cuts, "boundaries").select(F.posexplode("pivots").alias("j", "p")).select("j", F.col("p.c0_0").alias("value"), F.col("p.r0").alias("event_id"))


def single_sort_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.single_sort(load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", "p_partkey")


def single_scan_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.single_scan_min(_events(spark, sf_dir), "value")


def _local(spark: SparkSession, sf_dir: str, size: int, b: int, policy: str) -> DataFrame:
    """``(node, pivots)`` of all events, ``size`` to a node; the last node picks by the number of keys that are left for it."""
    h = portable_hash(7, 0, "pick", F.col("event_id"))
    rows = _events(spark, sf_dir).select(F.floor(F.col("event_id") / size).cast("int").alias("node"), F.struct(h.alias("h"), F.col("event_id").cast("string").alias("r"), F.struct("value", "event_id").alias("k")).alias("x"))
    samples = rows.groupBy("node").agg(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["k"]).alias("sample"))
    draw = lambda purpose, *more: portable_hash(7, 0, purpose, F.col("node"), *more)
    return samples.select("node", pick_pivots(F.col("sample"), b, draw, policy).alias("pivots"))


def _pivots(size: int, b: int, policy: str = "mixed") -> Query:
    return lambda spark, sf_dir: _local(spark, sf_dir, size, b, policy).select("node", F.posexplode("pivots").alias("j", "p")).select("node", "j", "p.value", "p.event_id")


def exact_median_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    local = _local(spark, sf_dir, 8, 8, "naive").select(F.lit(0).alias("grp"), "node", "pivots")
    return mediantree.exact_median(local).select(F.posexplode("pivots").alias("j", "p")).select("j", "p.value", "p.event_id")


def _bucket_profile(policy: str) -> Query:
    """Sizes times 8 of the buckets of all events between the medians of their nodes' pivots, eight keys a node and eight buckets."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        local = _local(spark, sf_dir, 8, 8, policy).select(F.lit(0).alias("grp"), "node", "pivots")
        cuts = staged(mediantree.exact_median(local).select("pivots"), "cuts")
        return measures.bucket_profile(baselines.cut_rows(_events(spark, sf_dir).select(F.struct("value", "event_id").alias("k")), cuts, 7), 8)

    return query


def udtf_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    from finegrain.functions.udfs import register

    register(spark)
    _events(spark, sf_dir).selectExpr("cast(event_id div 64 as int) AS node", "value AS k").createOrReplaceTempView("fg_keys_whole")
    rows = spark.sql("SELECT * FROM fg_pivots(4, TABLE(SELECT node, k FROM fg_keys_whole) PARTITION BY node)")
    return rows.select("node", "n", F.posexplode("pivots").alias("j", "pivot"))


# ------------------------------------------------------------- joins, sets, streams


def _outer(how: str) -> Query:
    return lambda spark, sf_dir: load(spark, sf_dir, "customer", ["c_custkey"]).join(load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), how)


def set_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_custkey"]).subtract(load(spark, sf_dir, "orders", ["o_custkey"]))


def stream_sorted_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events as one micro-batch of several files."""
    folder, out = fresh_path(spark, "stream-in"), fresh_path(spark, "stream-out")
    load(spark, sf_dir, "events").repartitionByRange(4, "event_id").write.parquet(f"{folder}/a")
    sink = lambda ranked, number: ranked.select("event_id", "value", "rank").withColumn("batch", F.lit(number)).write.mode("append").parquet(out)
    stream = merges.read_events(spark, f"{folder}/a", 4)
    merges.sorted_batches(stream, EVENT_KEY, SortConfig(16, 4, 4), sink, fresh_path(spark, "stream-state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("event_id long, value double, rank long, batch int").parquet(out)


PIVOTS = {
    "pivots_naive": (8, 8, "naive"), "pivots_shifted": (8, 8, "shifted"), "pivots_mixed": (8, 8, "mixed"), "pivots_case_equal": (16, 16, "mixed"),
    "pivots_case_short": (5, 8, "mixed"), "pivots_case_between": (12, 8, "mixed"), "pivots_case_double": (16, 8, "mixed"), "pivots_case_long": (40, 8, "mixed"),
}


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"tree_min_fanin_{f}": _tree(f) for f in (1, 2, 4, 8, 16, 32, 64)}
    out |= {"tree_max": _tree(8, "max"), **{name: _pivots(*given) for name, given in PIVOTS.items()}, **{f"join_{how}": _outer(how) for how in ("left", "right", "full")}}
    for f in (
        tree_count, tree_sum, tree_bit_or, tree_distinct_sketch, tree_min_by_type, tree_partials_level1, udaf_median, local_sort_small, bfs_rank_events, bfs_reduction_sweep, bfs_boundaries, single_sort_part,
        single_scan_min, exact_median_pivots, udtf_pivots, set_except, stream_sorted_batches,
    ):
        out[f.__name__] = f
    return {f"{name}_whole": query for name, query in out.items()} | {f"bucket_profile_{p}": _bucket_profile(p) for p in ("naive", "shifted", "mixed")}


def _profile_sql(policy: str) -> str:
    """Events between the lower medians of all nodes' pivots."""
    return f"""WITH r AS (SELECT *, row_number() OVER (PARTITION BY j ORDER BY value, event_id) AS pos, count(*) OVER (PARTITION BY j) AS m FROM ({_pivots_sql(8, 8, policy)})),
        c AS (SELECT list({{'v': value, 'i': event_id}}) AS cuts FROM r WHERE pos = (m + 1) // 2),
        e AS (SELECT len(list_filter(cuts, lambda x: x.v < value OR (x.v = value AND x.i <= event_id))) AS bucket FROM events, c)
        SELECT b::INT AS bucket, count(e.bucket) * 8 / (SELECT count(*) FROM e)::DOUBLE AS size FROM range(8) t(b) LEFT JOIN e ON e.bucket = b GROUP BY b"""


def _pivots_sql(size: int, b: int, policy: str) -> str:
    """Pivots ``(node, j, value, event_id)``; nodes of 2b keys take every second one, others leave one of b out."""
    some, low, _ = {"naive": NAIVE, "shifted": SHIFTED, "mixed": MIXED}[policy]
    ordered = "row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r"
    return f"""WITH h AS (SELECT event_id // {size} AS node, event_id, value, row_number() OVER (PARTITION BY event_id // {size} ORDER BY {digest(7, 0, 'pick', 'event_id')}, event_id::VARCHAR) AS h, count(*) OVER (PARTITION BY event_id // {size}) AS m FROM events),
        x AS (SELECT DISTINCT node, m FROM h WHERE m < {b}),
        s AS (SELECT node, value, event_id FROM h WHERE m < {2 * b} AND h <= {b} UNION ALL
              SELECT h.node, h.value, h.event_id FROM range(1, {b}) t(j) JOIN x ON j <= {b} - x.m JOIN h ON h.node = x.node AND h.h = {digest(7, 0, 'again', 'x.node', 'j')} % x.m + 1),
        o AS (SELECT *, {ordered}, {digest(7, 0, 'case', 'node')} / 4294967296.0 AS u, {digest(7, 0, 'drop', 'node')} % {b} AS d FROM s),
        k AS (SELECT * FROM o WHERE CASE WHEN u < {some} THEN r - 1 <> d WHEN u < {some + low} THEN r < {b} ELSE r > 1 END),
        w AS (SELECT node, value, event_id, {ordered}, CASE WHEN {digest(7, 0, 'set', 'node')} / 4294967296.0 < 0.5 THEN 0 ELSE 1 END AS s FROM h WHERE m >= {2 * b} AND h <= {2 * b})
        SELECT node::INT AS node, (row_number() OVER (PARTITION BY node ORDER BY r) - 1)::INT AS j, value, event_id FROM k UNION ALL
        SELECT node::INT, ((r - s) // 2 - 1)::INT, value, event_id FROM w WHERE (r - s) % 2 = 0 AND r - s BETWEEN 2 AND {2 * b - 2}"""


def oracle_sql() -> dict[str, str]:
    workers, nodes = (f"(SELECT (count(*) + {n - 1}) // {n} FROM events)" for n in (PER_WORKER, PER_NODE))
    rank = "row_number() OVER (ORDER BY value, event_id)"
    out = {f"tree_min_fanin_{f}": "SELECT min(value) AS value FROM events" for f in (1, 2, 4, 8, 16, 32, 64)}
    out |= {name: _pivots_sql(*given) for name, given in PIVOTS.items()}
    out |= {f"join_{how}": f"SELECT c_custkey, o_orderkey, o_custkey FROM customer {how} JOIN orders ON c_custkey = o_custkey" for how in ("left", "right", "full")}
    out |= {
        "tree_max": "SELECT max(value) AS value FROM events",
        "tree_count": "SELECT count(*) AS n FROM events",
        "tree_sum": "SELECT sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events",
        "tree_bit_or": "SELECT bit_or(user_id) AS user_id FROM events",
        "tree_min_by_type": "SELECT event_type, min(value) AS value FROM events GROUP BY 1",
        "tree_partials_level1": f"SELECT ((event_id % {workers}) // 8)::INT AS idx, min(value) AS least FROM events GROUP BY 1",
        "udaf_median": "SELECT event_type, quantile_disc(value, 0.5) AS mid FROM events GROUP BY 1",
        "local_sort_small": 'SELECT p_partkey // 40 AS task, (row_number() OVER (PARTITION BY p_partkey // 40 ORDER BY p_retailprice) - 1)::INT AS "at", p_retailprice AS price FROM part',
        "bfs_rank_events": f"SELECT event_id, value, {rank} - 1 AS rank FROM events",
        "bfs_boundaries": f"""WITH p AS (SELECT event_id, value, (row_number() OVER (ORDER BY {digest(7, 0, 'init', 'event_id')}, event_id::VARCHAR) - 1) % {nodes} AS node FROM events),
            o AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r, count(*) OVER (PARTITION BY node) AS m FROM p),
            s AS (SELECT o.value, o.event_id FROM o JOIN range(1, 9) t(j) ON o.r = greatest(1, ceil(j * m / 9.0))),
            a AS (SELECT *, {rank} AS r, count(*) OVER () AS m, {nodes} AS w FROM s)
            SELECT (j - 1)::INT AS j, value, event_id FROM a JOIN (SELECT unnest(range(1, {nodes})) AS j) t ON a.r = greatest(1, ceil(j * m / w::DOUBLE))""",
        "single_sort_part": "SELECT p_partkey, p_retailprice, row_number() OVER (ORDER BY p_retailprice, p_partkey) - 1 AS rank FROM part",
        "single_scan_min": "SELECT min(value) AS value FROM events",
        "exact_median_pivots": f"""WITH r AS (SELECT *, row_number() OVER (PARTITION BY j ORDER BY value, event_id) AS pos, count(*) OVER (PARTITION BY j) AS m FROM ({_pivots_sql(8, 8, 'naive')})),
            e AS (SELECT value, event_id FROM r WHERE pos = (m + 1) // 2)
            SELECT (row_number() OVER (ORDER BY value, event_id) - 1)::INT AS j, value, event_id FROM e""",
        "udtf_pivots": """WITH o AS (SELECT (event_id // 64)::INT AS node, value, row_number() OVER (PARTITION BY event_id // 64 ORDER BY value) AS r, count(*) OVER (PARTITION BY event_id // 64) AS n FROM events)
            SELECT node, n::INT AS n, (j - 1)::INT AS j, value AS pivot FROM o JOIN range(1, 4) t(j) ON r = greatest(1, (j * n + 3) // 4)""",
        "set_except": "SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders",
        "stream_sorted_batches": f"SELECT event_id, value, {rank} - 1 AS rank, 0 AS batch FROM events",
    }
    return {f"{name}_whole": sql for name, sql in out.items()} | {f"bucket_profile_{p}": _profile_sql(p) for p in ("naive", "shifted", "mixed")}
