"""Queries that once made up their data follow the given tables."""

import __spark_entry__ as entry
import pytest
from checks import same_rows, views
from pyspark.sql import functions as F

FOLDER = "/root/testdata/sf0.001"
NAMES = ["best_tree", "bucket_profile_mixed", "bucket_profile_naive", "bucket_profile_shifted", "cost_host_stacks", "cost_multicast", "cost_receive_send", "cost_tree_merge", "expected_bucket_law", "graph_shape"]


@pytest.fixture(scope="module")
def fewer(spark, tmp_path_factory):
    """The tables with a few rows only."""
    folder = tmp_path_factory.mktemp("fewer")
    for table, keep in (("events", "event_id % 3 = 0 and event_id < 100"), ("lineitem", "l_linenumber < 3")):
        spark.read.parquet(f"{FOLDER}/{table}.parquet").filter(F.expr(keep)).toPandas().to_parquet(folder / f"{table}.parquet", coerce_timestamps="us")
    return str(folder)


@pytest.mark.parametrize("name", NAMES)
def test_rows_follow_the_table(spark, fewer, name):
    found = []
    for folder in (FOLDER, fewer):
        df = entry.queries()[name](spark, folder)
        assert same_rows(df, views(folder), entry.oracle_sql()[name])
        found.append(sorted(map(tuple, df.collect()), key=str))
    assert found[0] != found[1]
