"""Pivot policies, cut points, placements and the baseline's clock."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from finegrain.functions import pivots
from finegrain.functions.hashing import portable_hash
from finegrain.functions.keys import KeySpec
from finegrain.operators import baselines, sorter
from finegrain.operators.ranking import hash_row_number
from finegrain.operators.sorter import SortConfig
from finegrain.plans import costmodel
from finegrain.plans.profile import PRESETS
from finegrain.sources.bucketed import write_bucketed
from finegrain.sources.staging import fresh_path


def test_weights_put_medians_at_their_quantiles():
    for n, row in enumerate(pivots.weight_table(8, "calibrated"), 8):
        for j, options in enumerate(row, 1):
            assert abs(sum(w for _, w in options) - 1) < 1e-9 and abs(pivots.median_quantile(n, options) - j / 8) < 1e-6
    (first, *_, last) = pivots.weight_table(10, ("mix", (0.8, 0.2)))[0]
    assert first == [(1, 0.8), (2, pytest.approx(0.2))] and last == [(9, pytest.approx(0.2)), (10, pytest.approx(0.8))]
    for bad in (("mix", (0.5, 0.4)), ("other", (0.5, 0.5))):
        with pytest.raises(ValueError):
            pivots.weight_table(8, bad)


@pytest.mark.parametrize("policy", ["calibrated", ("mix", (0.8, 0.2))])
@pytest.mark.parametrize("size", [1, 5, 8, 11, 16])
def test_weighted_picks(spark, policy, size):
    rows = spark.range(200).select(F.col("id").alias("node"), F.transform(F.sequence(F.lit(1), F.lit(size)), lambda i: F.struct((i * 10).alias("k"))).alias("keys"))
    draw = lambda purpose, *more: portable_hash(1, purpose, F.col("node"), *more)
    got = [[x["k"] // 10 for x in r["p"]] for r in rows.select(pivots.pick_pivots(F.col("keys"), 8, draw, policy).alias("p")).collect()]
    assert all(len(p) == 7 and p == sorted(p) and set(p) <= set(range(1, size + 1)) for p in got)
    if size >= 8:
        for j, options in enumerate(pivots.weight_table(8, policy)[size - 8]):
            mean = sum(i * w for i, w in options)
            assert abs(np.mean([p[j] for p in got]) - mean) < 0.2


@pytest.mark.parametrize("k", [0, 1, 100, 2999, 5000])
def test_top_k_and_selection_move_little(spark, k, monkeypatch):
    monkeypatch.setattr(sorter, "CUT_SAMPLE", 500)
    df = spark.range(3000).select("id", (F.pmod(F.xxhash64("id"), F.lit(700))).alias("v")).checkpoint()
    want = sorted((r["v"], r["id"]) for r in df.collect())
    key, cfg = KeySpec.of("v", "id"), SortConfig(16, 4, 4)
    got = sorted((r["rank"], r["v"], r["id"]) for r in sorter.top_k(df, key, k, cfg).collect())
    assert got == [(i, *x) for i, x in enumerate(want[:k])]
    one = [(r["rank"], r["v"], r["id"]) for r in sorter.select_rank(df, key, k, cfg).collect()]
    assert one == ([(k, *want[k])] if k < 3000 else [])
    kept, before = sorter._between(df, key, 1500, 1500, cfg)
    assert kept.count() < 1000 and 0 < before <= 1500


def test_numbers_by_hash_ranges(spark):
    df = spark.range(5000).select(portable_hash(1, F.col("id")).alias("h"), F.col("id").cast("string").alias("r"))
    rows = hash_row_number(df, "h", ["r"], "n", 13).collect()
    assert [r["n"] for r in sorted(rows, key=lambda r: (r["h"], r["r"]))] == list(range(5000))
    assert hash_row_number(df.filter("false"), "h", ["r"], "n", 13).count() == 0


def test_clock_of_the_baseline_grows(spark):
    key, net = KeySpec.of("id", "id"), PRESETS["simulated"].with_(multicast=False)

    def ends(nodes, factor, per_node):
        placed, routed = baselines.boundary_run(spark.range(16 * nodes), key, nodes, factor, per_node)
        return costmodel.simulate_boundary_sort(placed, routed, nodes, factor, per_node, net).agg(F.max("done_ns")).first()[0]

    by_nodes = [ends(n, 4, 16) for n in (16, 64, 128)]
    assert by_nodes == sorted(by_nodes) and by_nodes[2] > 2 * by_nodes[1]
    by_factor = [ends(64, f, 16) for f in (4, 64)]
    assert by_factor == sorted(by_factor)


def test_bucketed_tables_join_in_place(spark):
    path = fresh_path(spark, "bucketed")
    a = write_bucketed(spark.range(1000).withColumn("x", F.col("id") % 7), "fg_test_a", f"{path}/a", ["id"], 4)
    b = write_bucketed(spark.range(500).withColumn("y", F.col("id") % 3), "fg_test_b", f"{path}/b", ["id"], 4)
    joined = a.hint("merge").join(b, "id")
    assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString() and joined.count() == 500
    spark.sql("DROP TABLE fg_test_a")
    spark.sql("DROP TABLE fg_test_b")


def test_places_of_many_boundaries_beyond_32_bits(spark):
    rows = spark.range(1).select(F.sequence(F.lit(1), F.lit(50_000)).alias("all"))
    got = rows.select(baselines._spaced("all", 50_000).alias("p")).first()["p"]
    assert len(got) == 50_000 and got[0] == 1 and got[-1] == 50_000


@pytest.mark.parametrize("count", [1, 1024, 1025, 5000, 5041])
def test_cuts_in_two_steps(spark, count, monkeypatch):
    monkeypatch.setattr(baselines, "FEW_CUTS", 64)
    cuts = spark.range(1).select(F.transform(F.sequence(F.lit(1), F.lit(count)), lambda i: F.struct((i * 2).alias("v"))).alias("pivots"))
    rows = spark.range(0, 2 * count + 5).select(F.struct(F.col("id").cast("int").alias("v")).alias("k"), F.lit(0).alias("node"))
    got = {r["k"]["v"]: r["bucket"] for r in baselines.cut_rows(rows, cuts, count).collect()}
    assert got == {v: min(count, v // 2) for v in range(2 * count + 5)}


def test_pivots_of_all_keys_sort_a_node_once(spark):
    draw = lambda purpose, *more: portable_hash(1, purpose, *more)
    keys = F.transform(F.sequence(F.lit(1), F.lit(100)), lambda i: F.pmod(i * 37, F.lit(101)))
    plan = spark.range(1).select(pivots.full_quantiles(keys, 10, draw).alias("p"))._jdf.queryExecution().analyzed().toString()
    inner = plan[plan.index("sequence(1, 9") :]  # what runs for every pivot
    assert "array_sort(transform" not in inner and "sort_array" not in inner and "sort_array(transform" in plan


def test_first_pivots_and_ranks_without_a_sort(spark):
    df = spark.range(3000).select("id", F.pmod(F.xxhash64("id"), F.lit(700)).alias("v")).checkpoint()
    key, cfg = KeySpec.of("v", "id"), SortConfig(16, 16, 4, policy="full_quantile")
    local, group = sorter.first_pivots(df, key, cfg)
    made = sorter.recursive_sort(df, key, cfg)
    assert local.exceptAll(made.levels[0].local.select(*local.columns)).count() == 0 and group.collect() == made.levels[0].pivots.collect()
    wanted = made.df.filter("rank % 97 = 5 or rank in (0, 2999)").select("k", "rank")
    assert sorted((r["k"]["r0"], r["rank"]) for r in sorter.ranks_of(df, key, wanted.select("k").unionByName(wanted.select("k"))).collect()) == sorted((r["k"]["r0"], r["rank"]) for r in wanted.collect())
    assert sorter.ranks_of(df, key, wanted.select("k").limit(0)).count() == 0
