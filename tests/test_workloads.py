"""Cost model, small tasks, relational operators, sources and streams."""

import pytest
from checks import same_rows, views
from pyspark.sql import functions as F

from finegrain.functions.keys import KeySpec
from finegrain.operators import apps, microtasks, payload, relational
from finegrain.operators.components import connected_components
from finegrain.operators.ranking import global_row_number
from finegrain.operators.skew import join_group_facts
from finegrain.operators.sorter import SortConfig, recursive_sort
from finegrain.plans import costmodel, measures, relational_queries, workload_queries
from finegrain.plans.profile import PRESETS
from finegrain.sources import records
from finegrain.sources.staging import fresh_path
from finegrain.streaming import merges

FOLDER = "/root/testdata/sf0.001"


def test_fan_in_sweet_spot():
    p = PRESETS["tree_merge_published"]
    ns = {f: costmodel.tree_merge_ns(8192, 64, f, p) for f in (1, 2, 4, 8, 16, 32, 64)}
    assert min(ns, key=ns.get) == 8
    assert abs(ns[8] - 751) < 10 and abs(ns[64] - 866) < 10 and ns[1] > 10_000


def test_published_throughput(spark):
    rows = {r["system"]: r["computed"] for r in measures.published(spark).collect()}
    assert abs(rows["recursive bucket sort"] - 224) < 1


@pytest.fixture(scope="module")
def sorted_events(spark):
    events = spark.read.parquet(f"{FOLDER}/events.parquet").select("event_id", "value").filter("event_id < 512")
    return recursive_sort(events, KeySpec.of("value", "event_id"), SortConfig(16, 4, 4))


def test_clock_moves_with_network(spark, sorted_events):
    p = PRESETS["simulated"]
    ns = lambda q: costmodel.makespan(costmodel.simulate(sorted_events, q)).first()
    base = ns(p)
    slow, late, alone = ns(p.with_(switch_ns=1000.0)), ns(p.with_(tail_ns=4000.0, tail_share=0.05)), ns(p.with_(multicast=False))
    assert slow["sort_ns"] > base["sort_ns"] and slow["mean_idle_ns"] > base["mean_idle_ns"]
    assert late["sort_ns"] > base["sort_ns"] and alone["sort_ns"] > base["sort_ns"]
    assert costmodel.breakdown(costmodel.simulate(sorted_events, p)).count() == 4


def test_components(spark):
    edges = [(1, 2), (2, 3), (3, 4), (10, 11), (12, 11), (20, 21)] + [(100 + i, 101 + i) for i in range(40)] + [(7, 7)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got[4] == 1 and got[12] == 10 and got[21] == 20 and got[140] == 100 and 7 not in got
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_row_numbers(spark):
    df = spark.createDataFrame([(None, 1), (5, 1), (5, 0), (1, 9), (None, 0)] + [(i, 0) for i in range(10, 200)], "k long, t long")
    got = [(r["k"], r["t"]) for r in global_row_number(df, "k", ["t"], "n", 7).orderBy("n").collect()]
    assert got[:5] == [(None, 0), (None, 1), (1, 9), (5, 0), (5, 1)] and len(got) == 195
    assert global_row_number(df.limit(0), "k", ["t"], "n", 7).count() == 0


def test_skewed_facts(spark):
    rows = spark.range(5000).select(F.col("id"), F.when(F.col("id") < 3000, F.lit("hot")).otherwise(F.concat(F.lit("k"), F.col("id") % 700)).alias("key"))
    facts = rows.groupBy("key").agg(F.count("*").alias("w"))
    joined = join_group_facts(rows, facts, "key", "w", 5000, "id")
    assert joined.count() == 5000 and joined.filter("w is null").count() == 0
    assert joined.filter("key = 'hot'").agg(F.max("w")).first()[0] == 3000


def test_range_join_both_ways(spark):
    rows = spark.range(1000).select(F.col("id"), (F.col("id") / 10).alias("x"))
    ranges = spark.createDataFrame([(0, None, 20.0), (1, 20.0, 20.5), (2, 50.0, None)], "b int, lo double, hi double")
    a = relational.bucket_range_join(rows, ranges, "x").select("id", "b")
    b = relational.bucket_range_join(rows, ranges, "x", most_broadcast=0).select("id", "b")
    assert a.count() == 705 and a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_sorted_output_prunes(spark, tmp_path):
    df = spark.range(2000).select(F.col("id"), F.xxhash64("id").alias("x"))
    ranked = recursive_sort(df, KeySpec.of("x", "id"), SortConfig(16, 4, 4)).df
    path = fresh_path(spark, "out")
    payload.write_sorted(ranked.select("id", "x", "rank", "k"), path, 500, ["x", "id"])
    assert spark.read.parquet(f"{path}/keys").count() == 2000 == spark.read.parquet(f"{path}/values").count()
    found = payload.range_lookup(spark, f"{path}/keys", "x", 0, 2**62)
    assert found.count() == df.filter((F.col("x") >= 0) & (F.col("x") <= 2**62)).count()
    assert "PushedFilters" in found._jdf.queryExecution().executedPlan().toString()


def test_formats_and_records(spark):
    rows = records.records(spark, 100)
    assert rows.agg(F.max(F.length("payload"))).first()[0] == 96
    assert sorted(r["key"] for r in rows.collect()) == sorted(r["key"] for r in records.records(spark, 100, partitions=7).collect())
    for kind in ("csv", "json", "orc", "parquet"):
        path = fresh_path(spark, kind)
        records.write(rows, kind, path)
        assert records.read(spark, kind, path, rows.schema).exceptAll(rows).count() == 0


def test_set_algebra(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, "A, b!"), (3, "c"), (4, None), (5, "")], "id long, text string")
    ids = microtasks.word_ids(docs, "id", "text")
    assert {r["id"] for r in microtasks.intersect_sets(ids, ["a", "b"]).collect()} == {1, 2}
    assert {r["id"] for r in apps.boolean_search(docs, "id", "text", ["a"], ["c"]).collect()} == {2}


def test_late_rows_are_dropped(spark, tmp_path):
    early = "timestamp'2024-01-01 10:00:00'"
    path = fresh_path(spark, "late")
    for i, (at, v) in enumerate([(early, 5.0), ("timestamp'2024-01-03 10:00:00'", 4.0), ("timestamp'2024-01-04 10:00:00'", 3.0), ("timestamp'2024-01-01 10:10:00'", 1.0), ("timestamp'2024-01-05 10:00:00'", 2.0)]):
        spark.sql(f"SELECT {i}L AS event_id, {at} AS ts, 1L AS user_id, 'x' AS event_type, {v}D AS value, '' AS props").coalesce(1).write.mode("append").parquet(path)
        import time

        time.sleep(1.1)
    out = merges.drained(merges.windowed_min(merges.read_events(spark, path, 1), "1 hour"), "late_rows", fresh_path(spark, "state"))
    assert 5.0 in {r["least"] for r in out.collect()} and 1.0 not in {r["least"] for r in out.collect()}


def test_sessions(spark):
    events = spark.sql("SELECT explode(array(0, 100, 5000)) AS s").selectExpr("1L AS user_id", "timestamp_seconds(s) AS ts", "cast(s as double) AS value")
    assert merges.session_min(events, "10 minutes", None).count() == 2


NAMES = [
    "tree_min_by_type", "tree_partials_level1", "cost_tree_merge", "cost_multicast", "graph_shape", "throughput_table", "zorder_embeddings", "bounding_leaves", "kv_get_put", "boolean_search_documents",
    "median_tree_three_rounds", "granularity", "udaf_median", "scan_text", "stream_session_min", "join_as_of", "join_interval", "join_salted", "agg_grouping_sets", "win_offsets", "fn_dates", "fn_strings", "stream_tumbling_min", "stream_running_min",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    queries = workload_queries.queries() | relational_queries.queries()
    oracles = workload_queries.oracle_sql() | relational_queries.oracle_sql()
    assert same_rows(queries[name](spark, FOLDER), views(FOLDER), oracles[name])


def test_entry_without_llm(spark, monkeypatch):
    import importlib.util

    import __spark_entry__ as entry

    find = importlib.util.find_spec
    monkeypatch.setattr(importlib.util, "find_spec", lambda name, *a: None if name == "finegrain.llm" else find(name, *a))
    assert not any(q.startswith("op") or q == "pipeline" for q in entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() == 1500
