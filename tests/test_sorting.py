"""Exactness, invariants and stages of the recursive sort and its baselines."""

import math
from datetime import datetime
from decimal import Decimal

import pytest
from checks import same_rows, views
from pyspark.sql import Window
from pyspark.sql import functions as F

from finegrain.functions.keys import KeySpec
from finegrain.functions.pivots import calibrated_weights, expected_buckets, median_quantile
from finegrain.operators import baselines
from finegrain.operators.mediantree import best_fan_in
from finegrain.operators.placement import proportional
from finegrain.operators.sorter import SortConfig, global_rank, plan_levels, recursive_sort, select_rank, top_k
from finegrain.operators.treemerge import depth, tree_merge
from finegrain.plans import measures, messages
from finegrain.plans.profile import PRESETS
from finegrain.sources.tables import load

KEY = KeySpec.of("o_totalprice", "o_orderkey")


def expected(df, *order):
    return df.withColumn("want", F.row_number().over(Window.orderBy(*order)) - 1)


def wrong(ranked, want, on):
    return ranked.join(want.select(on, "want"), on).filter("rank <> want").count()


@pytest.mark.parametrize(
    "cfg",
    [
        SortConfig(16, 4, 4),
        SortConfig(16, 4, 2, policy="naive"),
        SortConfig(16, 16, 4, policy="shifted"),
        SortConfig(27, 3, 3, policy="full_quantile"),
        SortConfig(12, radices=(3, 4), seed=11),
        SortConfig(16, 4, 4, median="exact", rule="lower"),
        SortConfig(16, 4, 4, mode="physical", initial="round_robin", hash_name="fast"),
        SortConfig(16, 16, 4, mode="fused"),
        SortConfig(16, 4, 4, target_rows=450),
        SortConfig(4096, 16, 16),
    ],
    ids=lambda c: f"{c.mode}-{c.policy}-{c.nodes}-{c.target_rows}",
)
def test_ranks_are_exact(spark, small, cfg):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    result = recursive_sort(orders, KEY, cfg)
    assert result.df.count() == 1500
    assert wrong(result.df, expected(orders, "o_totalprice", "o_orderkey"), "o_orderkey") == 0


def test_edge_values(spark):
    rows = [(1, None), (2, float("nan")), (3, 0.0), (4, -0.0), (5, -5.5), (6, None), (7, math.inf), (8, -math.inf), (9, 0.0)]
    df = spark.createDataFrame(rows, "id int, x double")
    up = recursive_sort(df, KeySpec.of("x", "id"), SortConfig(4, 2, 2)).df
    assert wrong(up, expected(df, F.asc_nulls_first("x"), "id"), "id") == 0
    down = recursive_sort(df, KeySpec.of("-x", "id"), SortConfig(4, 2, 2)).df
    assert wrong(down, expected(df, F.desc_nulls_last("x"), "id"), "id") == 0
    last = recursive_sort(df, KeySpec.of("x", "id", nulls_first=False), SortConfig(4, 2, 2)).df
    assert wrong(last, expected(df, F.asc_nulls_last("x"), "id"), "id") == 0


def test_other_types(spark):
    rows = [(1, "ab", Decimal("1.5"), datetime(2020, 1, 1)), (2, "a", Decimal("-1.5"), datetime(2021, 1, 1)), (3, "", Decimal("0"), datetime(2019, 1, 1)), (4, "é", Decimal("9"), datetime(2020, 1, 2)), (5, None, None, None)]
    df = spark.createDataFrame(rows, "id int, s string, d decimal(5,2), t timestamp")
    for c in ("s", "d", "t"):
        down = recursive_sort(df, KeySpec.of(f"-{c}", "id"), SortConfig(4, 2, 2)).df
        assert wrong(down, expected(df, F.desc_nulls_last(c), "id"), "id") == 0, c
    with pytest.raises(TypeError):
        recursive_sort(df.withColumn("m", F.create_map("id", "s")), KeySpec.of("m", "id"), SortConfig(4, 2, 2))


@pytest.mark.parametrize("n", [0, 1, 3])
def test_few_rows(spark, n):
    df = spark.range(n).withColumn("x", F.lit(7))
    ranks = [r["rank"] for r in recursive_sort(df, KeySpec.of("x", "id"), SortConfig(8, 2, 2)).df.orderBy("id").collect()]
    assert ranks == list(range(n))


def test_nodes_must_match_levels():
    with pytest.raises(ValueError):
        SortConfig(10, 4).levels
    with pytest.raises(ValueError):
        SortConfig(10, radices=(3, 4)).levels


def test_invariants(spark, small):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    result = recursive_sort(orders, KEY, SortConfig(64, 8, 4))
    row = measures.verify_sorted(result.df).first()
    assert (row["inside"], row["across"], row["rows"], row["ranks"]) == (0, 0, 1500, 1500)
    moved = messages.key_messages(result)
    leaving = moved.filter((F.col("level") == 1) & (F.floor(F.col("src") / 8) != F.floor(F.col("dst") / 8))).count()
    assert leaving == 0
    assert {r["n"] for r in moved.groupBy("level").agg(F.sum("n_msgs").alias("n")).collect()} == {1500}
    for made in result.levels:
        lists = [r["pivots"] for r in made.local.collect()]
        assert all(list(p) == sorted(p) for p in lists if p)


def test_same_result_at_other_partitioning(spark, small):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    a = recursive_sort(orders, KEY, SortConfig(64, 8, 4)).df.select("o_orderkey", "node", "rank")
    b = recursive_sort(orders.repartition(7), KEY, SortConfig(64, 8, 4)).df.select("o_orderkey", "node", "rank")
    assert a.exceptAll(b).count() == 0


def test_selection(spark, small):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    want = [r["o_orderkey"] for r in orders.orderBy("o_totalprice", "o_orderkey").collect()]
    assert [r["o_orderkey"] for r in top_k(orders, KEY, 25, SortConfig(16, 4, 4)).orderBy("rank").collect()] == want[:25]
    for rank in (0, 700, 1499):
        assert [r["o_orderkey"] for r in select_rank(orders, KEY, rank, SortConfig(16, 4, 4)).collect()] == [want[rank]]
    assert select_rank(orders, KEY, 5000, SortConfig(16, 4, 4)).count() == 0


def test_baselines_agree(spark, small):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    want = expected(orders, "o_totalprice", "o_orderkey")
    for factor in (2, 4, 16):
        assert wrong(baselines.boundary_sort(orders, KEY, 32, factor), want, "o_orderkey") == 0
    assert wrong(baselines.single_sort(orders, "o_totalprice", "o_orderkey"), want, "o_orderkey") == 0


def test_proportional_nodes_cover_all(spark):
    counts = spark.createDataFrame([(0, 10), (1, 1000), (2, 1), (3, 989)], "bucket int, n long")
    rows = proportional(counts, 64).orderBy("bucket").collect()
    assert rows[0]["first_node"] == 0 and rows[-1]["first_node"] + rows[-1]["n_nodes"] == 64
    assert rows[1]["n_nodes"] > 30 and all(r["n_nodes"] >= 1 for r in rows)


def test_quantile_laws():
    assert abs(median_quantile(9, [(1, 1.0)]) - (1 - 0.5 ** (1 / 9))) < 1e-9
    assert abs(median_quantile(9, [(1, 0.8), (2, 0.2)]) - 0.0910) < 1e-4
    naive, shifted, mixed = (expected_buckets(p, 8) for p in ("naive", "shifted", "mixed"))
    assert abs(naive[0] - 0.754) < 1e-3 and abs(shifted[0] - 1.104) < 1e-3 and abs(mixed[0] - 1.008) < 1e-3
    assert max(mixed) - min(mixed) < max(shifted) - min(shifted) < max(naive) - min(naive)
    for j, options in enumerate(calibrated_weights(9, 10), 1):
        assert abs(median_quantile(9, options) - j / 10) < 1e-6
    assert abs(expected_buckets("mixed", 16)[0] - 1.012) < 1e-3


def test_spread_halves(spark):
    rows = {r["nodes"]: r["std"] for r in measures.pivot_quantile_spread(spark, [16, 256], 9, 5, 60).collect()}
    assert 2.5 < rows[16] / rows[256] < 6.5


def test_skew_falls_with_visibility(spark):
    total = {}
    for per_node in (4, 32):
        skews = []
        for seed in range(3):
            df = spark.range(256 * per_node).withColumn("x", F.xxhash64("id"))
            ranked = recursive_sort(df, KeySpec.of("x", "id"), SortConfig(256, 16, 16, seed=seed, hash_name="fast")).df
            skews.append(measures.skew(ranked, 256).first()["skew"])
        total[per_node] = sum(skews) / 3
    assert total[32] < total[4]


def test_multicast_share(spark):
    n = {m: messages.planned_ledger(spark, 4096, 131072, (16, 16, 16), PRESETS["simulated"].with_(multicast=m)).agg(F.sum("n_msgs")).first()[0] for m in (True, False)}
    assert abs(1 - n[True] / n[False] - 0.18) < 0.005
    assert n[False] == 5 * 131072 + 2 * 15 * 4096 * 3


def test_measured_ledger_matches_plan(spark, small):
    orders = load(spark, small, "orders", ["o_orderkey", "o_totalprice"])
    result = recursive_sort(orders, KEY, SortConfig(16, 4, 4))
    planned = messages.planned_ledger(spark, 16, 1500, (4, 4), PRESETS["simulated"])
    measured = messages.measured_ledger(result, PRESETS["simulated"])
    assert measured.exceptAll(planned.select(*measured.columns)).count() == 0


def test_tree_depth_and_merge(spark, small):
    assert (depth(64, 8), depth(64, 64), depth(64, 2), depth(64, 1), depth(1, 8), depth(1000, 10)) == (2, 1, 6, 63, 0, 3)
    assert 4 <= best_fan_in(64, 185.0) <= 16
    events = load(spark, small, "events", ["event_id", "value"])
    want = events.agg(F.min("value")).first()[0]
    for f in (1, 2, 7, 64):
        assert tree_merge(events, "value", "event_id", 64, f).first()[0] == want
    assert tree_merge(events, "value", "event_id", 64, 1, "max").first()[0] == events.agg(F.max("value")).first()[0]


def test_plans_have_no_single_partition(spark, small):
    orders = load(spark, small, "orders")
    result = recursive_sort(orders, KEY, SortConfig(64, 8, 4))
    plan = result.levels[0].routed._jdf.queryExecution().optimizedPlan().toString()
    assert "BatchEvalPython" not in plan
    ranked = global_rank(result.levels[-1].routed, 64)._jdf.queryExecution().executedPlan().toString()
    assert "BatchEvalPython" not in ranked
    scan = orders.select("o_orderkey", "o_totalprice")._jdf.queryExecution().executedPlan().toString()
    assert "o_orderdate" not in scan
    assert plan_levels(10**12, 100)[0] * plan_levels(10**12, 100)[1] >= 10**14 // (256 << 20)


STAGES = [
    "rbs_initial_shuffle", "rbs_final_counts", "rbs_level0_local_pivots", "rbs_level0_median_tree", "pivots_mixed", "pivots_case_short", "pivots_case_between", "pivots_case_double", "pivots_case_long",
    "exact_median_pivots", "bfs_boundaries", "proportional_nodes", "global_random_pivots",
]


@pytest.mark.parametrize("name", STAGES)
def test_stage_equals_sql(spark, name):
    from finegrain.plans import sorting_oracles, sorting_queries

    folder = "/root/testdata/sf0.01"
    assert same_rows(sorting_queries.queries()[name](spark, folder), views(folder), sorting_oracles.oracle_sql()[name])
