"""Small tasks that fit in a microsecond on one core: scans, small sorts, messages, point reads and writes, set intersections."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def tasks(df: DataFrame, position: str, size: int) -> DataFrame:
    """Add ``task``: rows by position, ``size`` to a task."""
    return df.withColumn("task", F.floor(F.col(position) / F.lit(size)).cast("long"))


def scan_words(df: DataFrame, value: str, position: str, words: int = 1024) -> DataFrame:
    """Sum, least and number of every task's words."""
    return tasks(df, position, words).groupBy("task").agg(F.sum(value).alias("total"), F.min(value).alias("least"), F.count("*").alias("n"))


def local_sort(df: DataFrame, value: str, position: str, keys: int = 40) -> DataFrame:
    """Every task's keys as a sorted array."""
    return tasks(df, position, keys).groupBy("task").agg(F.array_sort(F.collect_list(value)).alias("keys"))


def sort_runs(df: DataFrame, value: str, position: str, sizes: list[int], runs: int = 10) -> DataFrame:
    """``(size, run, keys)``: for every size the first ``runs`` tasks of so many rows, each sorted on its own."""
    wide = df.withColumn("size", F.explode(F.array(*map(F.lit, sizes)))).withColumn("run", F.floor(F.col(position) / F.col("size")).cast("int"))
    return wide.filter(F.col("run") < runs).groupBy("size", "run").agg(F.array_sort(F.collect_list(value)).alias("keys"))


def loopback(spark: SparkSession, messages: int = 118, workers: int = 64) -> DataFrame:
    """A ledger of messages that workers send to themselves."""
    return spark.range(workers).select(F.col("id").cast("int").alias("src"), F.col("id").cast("int").alias("dst"), F.lit(messages).cast("long").alias("n_msgs"), F.lit(16 * messages).cast("long").alias("n_bytes"))


def kv_get(store: DataFrame, requests: DataFrame, key: str) -> DataFrame:
    """Point reads: every request's key with its value, null where there is none."""
    return requests.join(store, key, "left")


def kv_put(store: DataFrame, updates: DataFrame, key: str) -> DataFrame:
    """Point writes: the store with the updates' rows in place of its own."""
    return store.join(updates.select(key), key, "left_anti").unionByName(updates)


def postings(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    """``(word, ids)``: sorted id lists of lower-cased words. A list is one value: for words in very many documents use the rows of
    ``word_ids``, as :func:`intersect_sets` does."""
    return word_ids(docs, id_col, text).groupBy("word").agg(F.array_sort(F.collect_list("id")).alias("ids"))


def word_ids(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    """Distinct ``(word, id)``."""
    words = F.array_distinct(F.filter(F.split(F.lower(F.col(text)), r"[^a-z]+"), lambda w: w != ""))
    return docs.select(F.col(id_col).alias("id"), F.explode(words).alias("word"))


def intersect_sets(lists: DataFrame, words: list[str]) -> DataFrame:
    """Ids that stand in the lists of all ``words``."""
    hit = lists.filter(F.col("word").isin(words))
    return hit.groupBy("id").agg(F.count_distinct("word").alias("n")).filter(F.col("n") == len(set(words))).select("id")


def top_of_each(df: DataFrame, by: str, order: str, n: int) -> DataFrame:
    """The first n rows of each group."""
    return df.withColumn("at", F.row_number().over(Window.partitionBy(by).orderBy(order))).filter(F.col("at") <= n)
