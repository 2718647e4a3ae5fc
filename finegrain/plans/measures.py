"""Accuracy and cost measures of sorts, pivots and runs."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain.functions.hashing import fraction, portable_hash


def skew(rows: DataFrame, nodes: int) -> DataFrame:
    """Most keys on a node over the mean, empty nodes included."""
    counts = rows.groupBy("node").agg(F.count("*").alias("n"))
    return counts.agg(F.max("n").alias("most"), (F.sum("n") / F.lit(float(nodes))).alias("mean"), (F.lit(nodes) - F.count("*")).cast("long").alias("empty")).withColumn("skew", F.col("most") / F.col("mean"))


def bucket_profile(bucketed: DataFrame, b: int) -> DataFrame:
    """``(bucket, size)``: share of all rows in each of ``b`` buckets, times b."""
    counts = bucketed.groupBy("bucket").agg(F.count("*").alias("n"))
    every = bucketed.sparkSession.range(b).select(F.col("id").cast("int").alias("bucket")).join(counts, "bucket", "left").na.fill({"n": 0})
    return every.select("bucket", (F.col("n") * b / F.sum("n").over(Window.partitionBy())).alias("size"))  # b rows


def pivot_quantile_spread(spark: SparkSession, nodes: Sequence[int], keys: int, rank: int, trials: int, seed: int = 3) -> DataFrame:
    """Mean and standard deviation over trials of the median over N nodes of the rank-th least of ``keys`` uniform keys."""
    out = None
    for n in nodes:
        grid = spark.range(trials * n).select(F.floor(F.col("id") / n).alias("trial"), F.col("id").alias("node"))
        each = grid.select("trial", F.get(F.array_sort(F.array(*(fraction(portable_hash(seed, n, i, F.col("node"))) for i in range(keys)))), rank - 1).alias("q"))
        med = each.groupBy("trial").agg(F.percentile("q", F.lit(0.5)).alias("q"))
        row = med.agg(F.lit(n).alias("nodes"), F.avg("q").alias("mean"), F.stddev_samp("q").alias("std"))
        out = row if out is None else out.unionByName(row)
    return out


def verify_sorted(ranked: DataFrame) -> DataFrame:
    """Inversions by rank inside nodes and across their borders, rows, and distinct ranks: no window over all rows."""
    inside = ranked.withColumn("_before", F.lag("k").over(Window.partitionBy("node").orderBy("rank")))
    bad = inside.agg(F.coalesce(F.sum(F.when(F.col("_before") > F.col("k"), 1).otherwise(0)), F.lit(0)).alias("inside"), F.count("*").alias("rows"), F.count_distinct("rank").alias("ranks"))
    edges = ranked.groupBy("node").agg(F.min("k").alias("lo"), F.max("k").alias("hi"))
    border = edges.withColumn("_prev", F.lag("hi").over(Window.orderBy("node"))).agg(F.coalesce(F.sum(F.when(F.col("_prev") > F.col("lo"), 1).otherwise(0)), F.lit(0)).alias("across"))
    return bad.crossJoin(border).select("inside", "across", "rows", "ranks")


def scan_bytes(df: DataFrame) -> tuple[int, int]:
    """Files and bytes that a plan reads: in place of cache misses, which Spark does not show."""
    jvm, conf = df.sparkSession.sparkContext._jvm, df.sparkSession.sparkContext._jsc.hadoopConfiguration()
    files = df.inputFiles()
    sizes = [jvm.org.apache.hadoop.fs.Path(f).getFileSystem(conf).getFileStatus(jvm.org.apache.hadoop.fs.Path(f)).getLen() for f in files]
    return len(files), sum(sizes)


def granularity_report(df: DataFrame, node: str = "node") -> dict:
    """The design rules as checks: even load, small tasks, no single-partition exchange, no row-wise Python."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    counts = df.groupBy(node).agg(F.count("*").alias("n")).agg(F.max("n").alias("most"), F.avg("n").alias("mean")).first()
    return {"single_partition": "SinglePartition" in plan, "row_python": "BatchEvalPython" in plan, "most": counts["most"], "load": (counts["most"] or 0) / (counts["mean"] or 1)}


def wall(fn: Callable[[], object]) -> float:
    began = time.perf_counter()
    fn()
    return time.perf_counter() - began


def repeated(fn: Callable[[int], float], seeds: Sequence[int]) -> dict:
    """Mean, standard deviation and most of ``fn`` over seeds."""
    xs = [fn(s) for s in seeds]
    mean = sum(xs) / len(xs)
    return {"mean": mean, "std": (sum((x - mean) ** 2 for x in xs) / max(1, len(xs) - 1)) ** 0.5, "most": max(xs), "runs": len(xs)}


def speedup(base: float, other: float) -> float:
    return base / other


# Published per-core efficiency (system, clock GHz, cores, threads a core, microseconds for 10**6 records, records per ms and core, records).
PUBLISHED = [
    ("recursive bucket sort", 3.2, 65536, 1, 68.0, 224, 1_000_000),
    ("boundary-first sort", 2.4, 2240, 1, 1000.0, 1297, 26_000_000),
    ("record-holding cluster sort", 2.9, 10240, 8, None, 1977, 10_000_000_000),
    ("in-memory cluster sort", 2.9, 3072, 2, None, 707, 10_000_000_000),
]


def published(spark: SparkSession) -> DataFrame:
    """The published table with the throughput that its own time and cores give."""
    rows = spark.createDataFrame(PUBLISHED, "system string, ghz double, cores int, threads int, us_for_million double, records_per_ms_core int, records long")
    return rows.withColumn("computed", F.round(F.lit(1e6) / (F.col("us_for_million") / 1000) / F.col("cores"), 1))
