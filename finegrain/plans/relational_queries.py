"""Registered queries of the surrounding operators: scans, joins, aggregates, windows, sets, functions, streams."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from finegrain.functions.keys import KeySpec
from finegrain.operators import relational
from finegrain.operators.sorter import SortConfig
from finegrain.sources import records
from finegrain.sources.bucketed import write_bucketed
from finegrain.sources.staging import fresh_path
from finegrain.sources.tables import load
from finegrain.streaming import merges

Query = Callable[[SparkSession, str], DataFrame]


def _scan_as(kind: str) -> Query:
    """The customers written and read in another format."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = load(spark, sf_dir, "customer", ["c_custkey", "c_name", "c_acctbal"])
        path = fresh_path(spark, f"as-{kind}")
        records.write(rows, kind, path)
        return records.read(spark, kind, path, rows.schema)

    return query


def scan_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").filter("l_quantity > 45 AND l_returnflag IN ('A', 'R')").select("l_orderkey", "l_quantity", "l_returnflag")


def scan_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region names through a text file."""
    path = fresh_path(spark, "as-text")
    load(spark, sf_dir, "region", ["r_name"]).write.text(path)
    return spark.read.text(path).withColumnRenamed("value", "r_name")


def stream_session_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's sessions with a gap of six hours, drained as a stream."""
    rows = _streamed(lambda e: merges.session_min(e, "6 hours", None), "complete")(spark, sf_dir)
    return rows.select("user_id", F.unix_seconds("start").alias("start_s"), F.unix_seconds("end").alias("end_s"), "least", "n")


def scan_record_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    spark.dataSource.register(records.RecordSource)
    rows = spark.read.format("finegrain_records").option("rows", 5000).load()
    return rows.agg(F.count("*").alias("n"), F.count_distinct("key").alias("keys"), F.max(F.length("payload")).alias("width"))


def join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).join(F.broadcast(load(spark, sf_dir, "nation", ["n_nationkey", "n_name"])), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


def join_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).hint("merge").join(load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


def join_shuffle_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).join(load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]).hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


def _outer(how: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        c = load(spark, sf_dir, "customer", ["c_custkey"]).filter("c_custkey < 600")
        o = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).filter("o_custkey > 300")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), how)

    return query


def join_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_custkey"]).join(load(spark, sf_dir, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


def join_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_custkey"]).join(load(spark, sf_dir, "orders", ["o_custkey"]).filter("o_custkey > 200"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


def join_parameter_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cross product of two parameter lists of fixed size."""
    return load(spark, sf_dir, "region", ["r_regionkey"]).crossJoin(F.broadcast(load(spark, sf_dir, "nation", ["n_nationkey"])))


def join_self(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    return n.alias("a").join(n.alias("b"), F.col("a.n_regionkey") == F.col("b.n_regionkey")).filter("a.n_nationkey < b.n_nationkey").select(F.col("a.n_nationkey").alias("x"), F.col("b.n_nationkey").alias("y"))


def join_range_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranges = spark.createDataFrame([(0, None, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, None)], "bucket int, lo double, hi double")
    return relational.bucket_range_join(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ranges, "o_totalprice").select("o_orderkey", "bucket")


def join_range_dealt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with the ranges dealt out instead of broadcast."""
    ranges = spark.createDataFrame([(0, None, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, None)], "bucket int, lo double, hi double")
    return relational.bucket_range_join(load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), ranges, "o_totalprice", most_broadcast=0).select("o_orderkey", "bucket")


def join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_returnflag"])
    flags = spark.createDataFrame([("A", 1), ("N", 2), ("R", 3)], "l_returnflag string, code int")
    return relational.salted_join(lines, flags, "l_returnflag").groupBy("code").agg(F.count("*").alias("n"))


def join_as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each even event with the last odd event of its user at or before it."""
    events = load(spark, sf_dir, "events", ["event_id", "ts", "user_id", "value"])
    left, right = events.filter("event_id % 2 = 0").select("event_id", "ts", "user_id"), events.filter("event_id % 2 = 1").select("user_id", "ts", "value")
    return relational.as_of_join(left, right, "ts", ["user_id"], ["value"]).select("event_id", "value_asof")


def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a user's purchases and clicks within two hours."""
    events = load(spark, sf_dir, "events", ["event_id", "ts", "user_id"])
    a = events.filter("event_id % 3 = 0").select(F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"), "user_id")
    b = events.filter("event_id % 3 = 1").select(F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"), "user_id")
    return relational.interval_join(a, b, "a_ts", "b_ts", ["user_id"], 7200).select("a_id", "b_id")


def agg_basic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.count_distinct("l_suppkey").alias("suppliers")
    )


def agg_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY o_totalprice)").alias("mid"), F.min_by("o_orderkey", "o_totalprice").alias("cheapest"), F.max_by("o_orderkey", "o_totalprice").alias("dearest"))


def agg_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.round(F.avg("o_totalprice"), 4).alias("mean"), F.round(F.stddev_samp("o_totalprice"), 4).alias("std"))


def agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.grouping_totals(load(spark, sf_dir, "lineitem"), "rollup", ["l_returnflag", "l_linestatus"], F.count("*").alias("n"))


def agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.grouping_totals(load(spark, sf_dir, "lineitem"), "cube", ["l_returnflag", "l_linestatus"], F.count("*").alias("n"))


def agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus"]).createOrReplaceTempView("fg_lines")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM fg_lines GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


def agg_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.histogram(load(spark, sf_dir, "orders", ["o_totalprice"]), "o_totalprice", 0, 500000, 10)


def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", ["o_orderstatus", "o_orderpriority"]).distinct()


def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem", ["l_partkey"]).agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_partkey", 0.5).alias("mid"))


def agg_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


def win_numbering(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    by_date = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(by_date).alias("rk"), F.dense_rank().over(by_date).alias("dr"), F.ntile(3).over(w).alias("third"))


def win_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


def win_offsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, sf_dir, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2).over(w).alias("after2"), F.first("value").over(full).alias("first"), F.last("value").over(full).alias("last"), F.nth_value("value", 2).over(full).alias("second"))


def win_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)
    span = Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-500, 0)
    return load(spark, sf_dir, "events").select("event_id", F.max("value").over(rows).alias("max3"), F.count("*").over(span).alias("near"))


def set_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_nationkey"]).unionByName(load(spark, sf_dir, "supplier", ["s_nationkey"]).withColumnRenamed("s_nationkey", "c_nationkey")).groupBy("c_nationkey").agg(F.count("*").alias("n"))


def set_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", ["o_custkey"]).filter("o_orderkey % 2 = 0").intersect(load(spark, sf_dir, "orders", ["o_custkey"]).filter("o_orderkey % 2 = 1"))


def set_intersect_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"])
    return o.filter("o_orderkey % 2 = 0").select("o_orderpriority").intersectAll(o.filter("o_orderkey % 3 = 0").select("o_orderpriority")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def set_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer", ["c_custkey"]).subtract(load(spark, sf_dir, "orders", ["o_custkey"]).filter("o_custkey < 700"))


def set_except_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"])
    return o.select("o_orderpriority").exceptAll(o.filter("o_orderkey % 3 = 0").select("o_orderpriority")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def sort_limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(30)


def fn_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").select(
        "c_custkey", F.length("c_name").alias("n"), F.substring("c_name", 1, 4).alias("head"), F.lower("c_mktsegment").alias("low"), F.upper("c_name").alias("up"), F.concat_ws("-", "c_name", "c_mktsegment").alias("both"),
        F.regexp_extract("c_name", r"(\d+)", 1).alias("digits"), F.md5("c_name").alias("md5"), F.sha2("c_name", 256).alias("sha"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"),
    )


def fn_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us"), F.datediff(F.lit("2000-01-01"), "o_orderdate").alias("days"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first"))


def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", F.pmod("o_custkey", F.lit(7)).alias("m"), F.shiftright("o_orderkey", 3).alias("s"), F.floor(F.col("o_totalprice") / 1000).alias("k"), F.round(F.log(F.col("o_totalprice")), 9).alias("ln"), F.round(F.sqrt("o_totalprice"), 9).alias("root"), F.greatest("o_orderkey", "o_custkey").alias("g"), F.col("o_orderkey").bitwiseXOR(F.col("o_custkey")).alias("x"))


def fn_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list("n_nationkey")).alias("a"))
    return rows.select(
        "n_regionkey", F.element_at("a", -1).alias("last"), F.size(F.filter("a", lambda x: x % 2 == 0)).alias("even"), F.aggregate("a", F.lit(0), lambda s, x: s + x).alias("total"), F.array_join(F.slice("a", 2, 3), ",").alias("mid"),
        F.array_join(F.transform("a", lambda x: x * 2), ",").alias("twice"), F.array_contains("a", 5).alias("has5"),
    )


def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    props = F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))
    return load(spark, sf_dir, "events").select("event_id", props["k"].alias("k"), F.get_json_object("props", "$.k").alias("text"))


# ------------------------------------------------------------- streams, drained over all files


def _streamed(make: Callable[[DataFrame], DataFrame], mode: str) -> Query:
    """Drain the event table as a stream and return its final rows."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        folder = fresh_path(spark, "stream-in")
        load(spark, sf_dir, "events").repartitionByRange(4, "event_id").write.parquet(folder)
        name = "fg_" + folder.rsplit("-", 1)[1]
        return merges.drained(make(merges.read_events(spark, folder, 4)), name, fresh_path(spark, "stream-state"), mode)

    return query


def stream_running_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's least value and number of events after the whole stream."""
    updates = _streamed(merges.running_min, "update")(spark, sf_dir)
    return updates.groupBy("user_id").agg(F.min("least").alias("least"), F.max("n").alias("n"))


def stream_sorted_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Micro-batches sorted by the recursive sort, ranks within each."""
    folder, out = fresh_path(spark, "stream-in"), fresh_path(spark, "stream-out")
    events = load(spark, sf_dir, "events")
    events.filter("event_id < 5000").coalesce(1).write.parquet(f"{folder}/a")
    sink = lambda ranked, number: ranked.select("event_id", "value", "rank").withColumn("batch", F.lit(number)).write.mode("append").parquet(out)
    stream = merges.read_events(spark, f"{folder}/a", 1)
    query = merges.sorted_batches(stream, KeySpec.of("value", "event_id"), SortConfig(16, 4, 4), sink, fresh_path(spark, "stream-state")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema("event_id long, value double, rank long, batch int").parquet(out)


def sink_bucketed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines and revenue of every order from two tables bucketed by the order: joined and summed without an exchange."""
    name, path = f"fg_{uuid.uuid4().hex}", fresh_path(spark, "bucketed")
    orders = write_bucketed(load(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"]), f"{name}_o", f"{path}/orders", ["o_orderkey"], 8)
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity"]).withColumnRenamed("l_orderkey", "o_orderkey")
    lines = write_bucketed(lines, f"{name}_l", f"{path}/lines", ["o_orderkey"], 8)
    return orders.hint("merge").join(lines, "o_orderkey").groupBy("o_orderkey", "o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"scan_{kind}": _scan_as(kind) for kind in ("csv", "json", "orc", "parquet")}
    out |= {"join_left": _outer("left"), "join_right": _outer("right"), "join_full": _outer("full")}
    seconds = lambda df: df.select(F.unix_seconds("start").alias("start_s"), F.unix_seconds("end").alias("end_s"), "least", "n")
    out |= {
        "stream_tumbling_min": lambda s, d: seconds(_streamed(lambda e: merges.windowed_min(e, "1 hour", watermark=None), "complete")(s, d)),
        "stream_sliding_min": lambda s, d: seconds(_streamed(lambda e: merges.windowed_min(e, "2 hours", "1 hour", None), "complete")(s, d)),
        "stream_dedup": lambda s, d: _streamed(lambda e: merges.deduplicated(e), "append")(s, d).select("event_id", "value"),
        "stream_static_join": lambda s, d: _streamed(lambda e: merges.joined_static(e, s.range(75).withColumnRenamed("id", "user_id").withColumn("known", F.lit(1)), "user_id"), "append")(s, d).select("event_id", "known"),
    }
    for f in (
        sink_bucketed, scan_pruned, scan_text, stream_session_min, scan_record_source, join_broadcast, join_merge, join_shuffle_hash, join_semi, join_anti, join_parameter_grid, join_self, join_range_buckets, join_range_dealt, join_salted, join_as_of, join_interval,
        agg_basic, agg_median, agg_spread, agg_rollup, agg_cube, agg_grouping_sets, agg_histogram, agg_distinct, agg_approx_distinct, agg_lists, win_numbering, win_distribution, win_offsets, win_frames,
        set_union, set_intersect, set_intersect_all, set_except, set_except_all, sort_limit_offset, fn_strings, fn_dates, fn_math, fn_arrays, fn_json, stream_running_min, stream_sorted_batches,
    ):
        out[f.__name__] = f
    return out


def oracle_sql() -> dict[str, str]:
    customers = "SELECT c_custkey, c_name, c_acctbal FROM customer"
    outer = lambda how: f"SELECT c_custkey, o_orderkey, o_custkey FROM (SELECT * FROM customer WHERE c_custkey < 600) c {how} JOIN (SELECT * FROM orders WHERE o_custkey > 300) o ON c_custkey = o_custkey"
    ranges = "SELECT o_orderkey, CASE WHEN o_totalprice < 50000 THEN 0 WHEN o_totalprice < 150000 THEN 1 WHEN o_totalprice < 300000 THEN 2 ELSE 3 END AS bucket FROM orders"
    segment = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"
    out = {f"scan_{kind}": customers for kind in ("csv", "json", "orc", "parquet")}
    out |= {
        "sink_bucketed": "SELECT o_orderkey, o_orderpriority, count(*) AS n, sum(l_quantity) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL",
        "scan_pruned": "SELECT l_orderkey, l_quantity, l_returnflag FROM lineitem WHERE l_quantity > 45 AND l_returnflag IN ('A', 'R')",
        "scan_text": "SELECT r_name FROM region",
        "stream_session_min": """WITH g AS (SELECT *, sum(CASE WHEN epoch_us(ts) - lag_us < 21600000000 THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT *, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS lag_us FROM events))
            SELECT user_id, min(epoch_us(ts)) // 1000000 AS start_s, (max(epoch_us(ts)) + 21600000000) // 1000000 AS end_s, min(value) AS least, count(*) AS n FROM g GROUP BY user_id, s""",
        "scan_record_source": "SELECT 5000 AS n, 5000 AS keys, 96 AS width",
        "join_broadcast": "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey",
        "join_merge": segment,
        "join_shuffle_hash": segment,
        "join_left": outer("LEFT"),
        "join_right": outer("RIGHT"),
        "join_full": outer("FULL"),
        "join_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
        "join_anti": "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey > 200)",
        "join_parameter_grid": "SELECT r_regionkey, n_nationkey FROM region, nation",
        "join_self": "SELECT a.n_nationkey AS x, b.n_nationkey AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
        "join_range_buckets": ranges,
        "join_range_dealt": ranges,
        "join_salted": "SELECT CASE l_returnflag WHEN 'A' THEN 1 WHEN 'N' THEN 2 ELSE 3 END AS code, count(*) AS n FROM lineitem GROUP BY 1",
        "join_as_of": "SELECT a.event_id, b.value AS value_asof FROM (SELECT * FROM events WHERE event_id % 2 = 0) a ASOF LEFT JOIN (SELECT * FROM events WHERE event_id % 2 = 1) b ON a.user_id = b.user_id AND a.ts >= b.ts",
        "join_interval": "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id % 3 = 0 AND b.event_id % 3 = 1 AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 7200000000",
        "agg_basic": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS qty, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY ALL",
        "agg_median": "SELECT o_orderpriority, quantile_disc(o_totalprice, 0.5) AS mid, min_by(o_orderkey, o_totalprice) AS cheapest, max_by(o_orderkey, o_totalprice) AS dearest FROM orders GROUP BY ALL",
        "agg_spread": "SELECT o_orderpriority, round(avg(o_totalprice), 4) AS mean, round(stddev_samp(o_totalprice), 4) AS std FROM orders GROUP BY ALL",
        "agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
        "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
        "agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
        "agg_histogram": "SELECT CASE WHEN o_totalprice < 0 THEN 0 ELSE least(11, floor(o_totalprice / 50000)::BIGINT + 1) END AS bin, count(*) AS n FROM orders GROUP BY 1",
        "agg_distinct": "SELECT DISTINCT o_orderstatus, o_orderpriority FROM orders",
        "agg_lists": "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1",
        "win_numbering": "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr, ntile(3) OVER w AS third FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)",
        "win_distribution": "SELECT o_orderkey, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)",
        "win_offsets": 'SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS after2, first_value(value) OVER f AS "first", last_value(value) OVER f AS "last", nth_value(value, 2) OVER f AS "second" FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id), f AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)',
        "win_frames": "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS max3, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near FROM events",
        "set_union": "SELECT c_nationkey, count(*) AS n FROM (SELECT c_nationkey FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1",
        "set_intersect": "SELECT o_custkey FROM orders WHERE o_orderkey % 2 = 0 INTERSECT SELECT o_custkey FROM orders WHERE o_orderkey % 2 = 1",
        "set_intersect_all": "SELECT o_orderpriority, count(*) AS n FROM (SELECT o_orderpriority FROM orders WHERE o_orderkey % 2 = 0 INTERSECT ALL SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 0) GROUP BY 1",
        "set_except": "SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_custkey < 700",
        "set_except_all": "SELECT o_orderpriority, count(*) AS n FROM (SELECT o_orderpriority FROM orders EXCEPT ALL SELECT o_orderpriority FROM orders WHERE o_orderkey % 3 = 0) GROUP BY 1",
        "sort_limit_offset": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 30 OFFSET 20",
        "fn_strings": "SELECT c_custkey, length(c_name)::INT AS n, substr(c_name, 1, 4) AS head, lower(c_mktsegment) AS low, upper(c_name) AS up, concat_ws('-', c_name, c_mktsegment) AS both_, regexp_extract(c_name, '([0-9]+)', 1) AS digits, md5(c_name) AS md5, sha256(c_name) AS sha, lpad(c_custkey::VARCHAR, 8, '0') AS padded FROM customer".replace("both_", '"both"'),
        "fn_dates": "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, epoch_us(o_orderdate) AS us, date_diff('day', o_orderdate::DATE, DATE '2000-01-01')::INT AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS \"first\" FROM orders",
        "fn_math": "SELECT o_orderkey, o_custkey % 7 AS m, o_orderkey >> 3 AS s, floor(o_totalprice / 1000)::BIGINT AS k, round(ln(o_totalprice), 9) AS ln, round(sqrt(o_totalprice), 9) AS root, greatest(o_orderkey, o_custkey) AS g, xor(o_orderkey, o_custkey) AS x FROM orders",
        "fn_arrays": "WITH r AS (SELECT n_regionkey, list_sort(list(n_nationkey)) AS a FROM nation GROUP BY 1) SELECT n_regionkey, a[-1] AS \"last\", len(list_filter(a, lambda x: x % 2 = 0))::INT AS even, list_sum(a)::INT AS total, array_to_string(a[2:4], ',') AS mid, array_to_string(list_transform(a, lambda x: x * 2), ',') AS twice, list_contains(a, 5) AS has5 FROM r",
        "fn_json": "SELECT event_id, (props->>'$.k')::BIGINT AS k, props->>'$.k' AS text FROM events",
        "stream_tumbling_min": "SELECT (epoch_us(ts) // 3600000000) * 3600 AS start_s, (epoch_us(ts) // 3600000000) * 3600 + 3600 AS end_s, min(value) AS least, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_sliding_min": "SELECT s AS start_s, s + 7200 AS end_s, min(value) AS least, count(*) AS n FROM (SELECT value, unnest([(epoch_us(ts) // 3600000000) * 3600, (epoch_us(ts) // 3600000000) * 3600 - 3600]) AS s FROM events) GROUP BY 1, 2",
        "stream_dedup": "SELECT event_id, value FROM events",
        "stream_static_join": "SELECT event_id, CASE WHEN user_id < 75 THEN 1 END AS known FROM events",
        "stream_running_min": "SELECT user_id, min(value) AS least, count(*) AS n FROM events GROUP BY 1",
        "stream_sorted_batches": "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) - 1 AS rank, 0 AS batch FROM events WHERE event_id < 5000",
    }
    return out
