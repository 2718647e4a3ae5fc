"""SQL functions of the sorter, and Python forms for cross-checks."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf


def register(spark: SparkSession) -> None:
    """``fg_hash``, ``fg_bucket``, ``fg_node`` as SQL functions (expressions, no Python) and the table function ``fg_pivots``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fg_hash(parts STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(CAST(parts AS BINARY)), 1, 8), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fg_bucket(k DOUBLE, pivots ARRAY<DOUBLE>) RETURNS INT RETURN size(filter(pivots, p -> p <= k))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fg_node(first INT, width INT, buckets INT, bucket INT, h BIGINT) RETURNS INT RETURN CAST(first + bucket * (width div buckets) + pmod(h, width div buckets) AS INT)")
    spark.udtf.register("fg_pivots", NodePivots)


@udtf(returnType=T.StructType([T.StructField("node", T.IntegerType()), T.StructField("n", T.IntegerType()), T.StructField("pivots", T.ArrayType(T.DoubleType()))]))
class NodePivots:
    """Takes the number of buckets and ``TABLE(SELECT node, k ...) PARTITION BY node``; evenly spaced pivots of each node."""

    def __init__(self):
        self._keys, self._node, self._b = [], None, 2

    def eval(self, buckets: int, row):
        self._node, self._b = row["node"], buckets
        self._keys.append(float(row["k"]))

    def terminate(self):
        if self._keys:
            ordered, n = sorted(self._keys), len(self._keys)
            yield self._node, n, [ordered[max(0, -(-j * n // self._b) - 1)] for j in range(1, self._b)]


@F.pandas_udf(T.DoubleType())
def median_element(values: pd.Series) -> float:
    """Grouped aggregate: the lower median element."""
    ordered = values.sort_values(ignore_index=True)
    return float(ordered.iloc[(len(ordered) - 1) // 2])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def spaced_pivots(keys: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """Evenly spaced quartiles of each array of keys, as a cross-check of the expression form."""
    for batch in keys:
        yield batch.map(lambda a: [sorted(a)[max(0, -(-j * len(a) // 4) - 1)] for j in range(1, 4)])
