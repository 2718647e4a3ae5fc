"""Whole-table forms of the queries that have an experiment's size."""

import __spark_entry__ as entry
import pytest
from checks import same_rows, views

FOLDER = "/root/testdata/sf0.01"  # more rows than the experiments take
WHOLE = sorted(n for n in entry.oracle_sql() if n.endswith("_whole"))
PREFIXES = [
    *(f"tree_min_fanin_{f}" for f in (1, 2, 4, 8, 16, 32, 64)), "tree_max", "tree_count", "tree_sum", "tree_bit_or", "tree_distinct_sketch", "tree_min_by_type", "tree_partials_level1", "udaf_median", "local_sort_small",
    "bfs_rank_events", "bfs_reduction_sweep", "bfs_boundaries", "single_sort_part", "single_scan_min", "exact_median_pivots", "udtf_pivots", "stream_sorted_batches", "join_left", "join_right", "join_full", "set_except",
    *(f"pivots_{k}" for k in ("naive", "shifted", "mixed", "case_equal", "case_short", "case_between", "case_double", "case_long")),
]


def test_every_prefix_query_has_a_whole_form():
    assert {f"{n}_whole" for n in PREFIXES} <= set(entry.queries())


@pytest.mark.parametrize("name", WHOLE)
def test_whole_tables(spark, name):
    assert same_rows(entry.queries()[name](spark, FOLDER), views(FOLDER), entry.oracle_sql()[name])


def test_whole_forms_without_sql(spark):
    found, events = entry.queries(), spark.read.parquet(f"{FOLDER}/events.parquet")
    for r in found["bfs_reduction_sweep_whole"](spark, FOLDER).collect():
        assert round(r["mean"] * r["nodes"]) == events.count()
    users = events.select("user_id").distinct().count()
    assert abs(found["tree_distinct_sketch_whole"](spark, FOLDER).first()["users"] - users) <= 0.1 * users
