"""Equi-joins that stay balanced when a few keys hold most rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key is heavy when it holds this share of all rows; at most its inverse many keys can be.
HEAVY_SHARE = 1 / 1000
SALTS = 64


def join_group_facts(rows: DataFrame, facts: DataFrame, key: str, weight: str, total: int, spread: str, how: str = "left") -> DataFrame:
    """Join ``facts`` (one row a key, ``weight`` = its rows) to ``rows`` by ``key``; null keys match nothing.

    Heavy keys, at most ``1 / HEAVY_SHARE`` of them whatever the size of the data, are known by a broadcast
    list; their rows are spread over ``SALTS`` tasks by ``spread`` and their facts are repeated as often.
    """
    heavy = facts.filter(F.col(weight) >= max(2, int(total * HEAVY_SHARE))).select(key).withColumn("_heavy", F.lit(True))
    flagged = rows.join(F.broadcast(heavy), key, "left")
    salt = F.when(F.col("_heavy"), F.pmod(F.xxhash64(spread), F.lit(SALTS)).cast("int")).otherwise(0)
    copies = F.when(F.col(weight) >= max(2, int(total * HEAVY_SHARE)), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    wide = facts.withColumn("_salt", F.explode(copies))
    return flagged.withColumn("_salt", salt).join(wide, [key, "_salt"], how).drop("_salt", "_heavy")
