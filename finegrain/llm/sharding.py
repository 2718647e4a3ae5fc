"""Reproducible shuffle into shards: a Feistel permutation with cycle walking over global row numbers.

Rows are numbered in the order of a hash of id, size and checksum; row ``i`` of that order gets the permuted number ``p``; its shard is
``p mod shards`` and its slot ``p div shards``. Both can be computed for any row number, and back, without a table, and shard
sizes differ by one at most.

The network works on pairs of a mixed radix ``a * b >= rows`` with ``a`` and ``b`` near the square root, so that
few numbers fall outside and the walk back into range is short and always ends.

Numbering: equal ranges of the hash are sorted side by side, as many as the rows need. Rows that agree in id, size and checksum have one
hash and are interchangeable; where they are many, a salt written down with the rows deals them out over further ranges.

Defined results: null ids and texts are values like any other; a null text has size 16 and the checksum of the empty text. Rows
that agree in id, size and checksum are interchangeable. An empty table gives an empty table.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from finegrain.llm.rows import column
from finegrain.sources.staging import staged

ROUNDS = 6
KEY = 20240917
#: Rows that one range of the global numbering is meant to hold; salts of rows that are alike.
RANGE_ROWS, SALTS = 20_000, 256


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit mixing function of the round's half block."""
    with np.errstate(over="ignore"):
        z = x.astype(np.uint64) + np.uint64((salt * 0x9E3779B97F4A7C15) % 2**64)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


def radices(rows: int) -> tuple[int, int]:
    """The two radices of the network's domain for so many rows."""
    a = max(1, math.isqrt(max(rows, 1)))
    return a, max(1, -(-max(rows, 1) // a))


def _network(x: np.ndarray, a: int, b: int, key: int, inverse: bool) -> np.ndarray:
    left, right = (x // b).astype(np.uint64), (x % b).astype(np.uint64)
    ua, ub = np.uint64(a), np.uint64(b)
    for k in reversed(range(ROUNDS)) if inverse else range(ROUNDS):
        if k % 2:
            step = _mixed(left, key + k) % ub
            right = (right + (ub - step if inverse else step)) % ub
        else:
            step = _mixed(right, key + k) % ua
            left = (left + (ua - step if inverse else step)) % ua
    return (left * ub + right).astype(np.int64)


def permute(numbers: np.ndarray, rows: int, key: int = KEY, inverse: bool = False) -> np.ndarray:
    """The keyed permutation of ``0 .. rows - 1`` (or its inverse): walk the cycle until back in range."""
    a, b = radices(rows)
    out = _network(np.asarray(numbers, dtype=np.int64), a, b, key, inverse)
    while (outside := out >= rows).any():
        out[outside] = _network(out[outside], a, b, key, inverse)
    return out


def row_numbers(narrow: DataFrame, rows: int, range_rows: int = RANGE_ROWS) -> DataFrame:
    """``narrow`` (a table with the 64-bit ``hash`` and the ``salt`` of its ``rows`` rows) with ``row_number`` from 0, in order of hash."""
    ranges = rows // range_rows + 1
    # the high 62 bits as a share of the whole: equal ranges without a look at the rows
    top = lambda h: F.floor((F.shiftright(h, 2) + F.lit(1 << 61)) / F.lit(2.0**62) * F.lit(ranges)).cast("long")
    # hashes of very many rows: as many as fit into the rows, one for every 4 * range_rows at most
    often = narrow.groupBy("hash").agg(F.count("*").alias("n")).filter(F.col("n") > 4 * range_rows)
    hot = staged(often.select(F.least(top(F.col("hash")), F.lit(ranges - 1)).alias("part"), "hash").groupBy("part").agg(F.array_sort(F.collect_list("hash")).alias("hot")), "hot-rows")
    placed = narrow.withColumn("part", F.least(top(F.col("hash")), F.lit(ranges - 1))).join(F.broadcast(hot), "part", "left")
    below = F.coalesce(F.size(F.filter("hot", lambda h: h < F.col("hash"))), F.lit(0))
    alike = F.coalesce(F.array_contains("hot", F.col("hash")), F.lit(False))
    # inside a range: rows before the first hot hash, its salts, rows after it, and so on
    placed = placed.withColumn("sub", below * 2 * SALTS + F.when(alike, F.lit(SALTS) + F.col("salt")).otherwise(0)).drop("hot")
    inside = F.row_number().over(Window.partitionBy("part", "sub").orderBy("hash")).cast("long") - 1
    sizes = placed.groupBy("part", "sub").agg(F.count("*").alias("n"))
    # one row for each range, for every RANGE_ROWS rows or so: prefix sums over blocks of ranges, then over blocks
    blocks = F.floor(F.col("part") / F.lit(math.isqrt(ranges) + 1))
    sizes = sizes.withColumn("block", blocks)
    in_block = sizes.withColumn("before", F.sum("n").over(Window.partitionBy("block").orderBy("part", "sub")) - F.col("n"))
    per_block = sizes.groupBy("block").agg(F.sum("n").alias("rows"))
    starts = per_block.select("block", (F.sum("rows").over(Window.orderBy("block")) - F.col("rows")).alias("start"))
    starts = in_block.join(F.broadcast(starts), "block").select("part", "sub", (F.col("before") + F.col("start")).alias("start"))
    numbered = placed.withColumn("at", inside).join(starts, ["part", "sub"])
    return numbered.withColumn("row_number", F.col("at") + F.col("start")).drop("part", "sub", "at", "start")


def sharded_documents(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text: str = "text", key: int = KEY, range_rows: int = RANGE_ROWS) -> DataFrame:
    """Shard, slot, size and checksum of every document under the law ``rows``."""
    body = F.coalesce(column(text), F.lit(""))
    narrow = docs.select(column(id_col).alias("id"), (F.octet_length(body) + 16).cast("long").alias("size"), F.crc32(F.encode(body, "UTF-8")).alias("text_crc32"))
    narrow = narrow.select("*", F.xxhash64("id", "size", "text_crc32").alias("hash"), F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int").alias("salt"))
    narrow = staged(narrow, "sizes")
    rows = narrow.count()

    @F.pandas_udf("long")
    def permuted(number: pd.Series) -> pd.Series:
        return pd.Series(permute(number.to_numpy(), rows, key))

    placed = row_numbers(narrow, rows, range_rows).withColumn("p", permuted("row_number"))
    shard, slot = F.pmod("p", F.lit(shards)).cast("int").alias("shard"), F.floor(F.col("p") / F.lit(shards)).cast("long").alias("slot")
    return placed.select(F.col("id").alias(id_col), "size", "text_crc32", F.lit("rows").alias("law"), shard, slot, F.lit(None).cast("int").alias("grown_shard"), "row_number")
