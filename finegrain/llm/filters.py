"""Bit tables: prefilters that let most rows pass without a shuffle.

A table has eight slots a key up to a bound, so what is broadcast is bounded whatever the number of keys. A table that is full lets more
rows through to the join behind it and changes no result.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: log2 of a table's slots at least and, for tables of broadcast rows and of Python workers, at most: 2**20 words and 32 MB.
LEAST_BITS, MOST_BITS, MOST_ARRAY_BITS = 12, 26, 28


def slot_bits_for(keys: int, most: int = MOST_BITS) -> int:
    """log2 of the slots of a table for so many keys."""
    return min(most, max(LEAST_BITS, (8 * max(keys, 1) - 1).bit_length()))


def slot_of(key: str | Column, bits: int) -> Column:
    """The slot of a 64-bit key."""
    return F.pmod(F.col(key) if isinstance(key, str) else key, F.lit(1 << bits))


def bit_words(slots: DataFrame) -> DataFrame:
    """``(word, bits)`` with the bits of all ``slot`` values set: at most a 64th as many rows as there are slots."""
    return slots.groupBy(F.shiftrightunsigned("slot", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot & 63L as int))")).alias("bits"))


def tested(rows: DataFrame, slot: Column, words: DataFrame) -> DataFrame:
    """``rows`` with ``maybe``: false where the table of ``words`` proves that the row's slot is not set.

    ``rows`` must have no columns ``slot``, ``word`` and ``bits``. The words are broadcast: ``2**(MOST_BITS - 6)`` at most.
    """
    met = rows.withColumn("slot", slot).withColumn("word", F.shiftrightunsigned("slot", 6)).join(F.broadcast(words), "word", "left")
    hit = F.coalesce(F.expr("(shiftrightunsigned(bits, cast(slot & 63L as int)) & 1L) = 1L"), F.lit(False))
    return met.withColumn("maybe", hit).drop("slot", "word", "bits")


def split_by_keys(rows: DataFrame, keys: DataFrame, key: str) -> tuple[DataFrame, DataFrame]:
    """``rows`` whose 64-bit ``key`` is certainly not among ``keys`` (a table), and those where it may be; neither shuffles."""
    bits = slot_bits_for(keys.count())
    marked = tested(rows, slot_of(key, bits), bit_words(keys.select(slot_of(key, bits).alias("slot"))))
    return marked.filter("not maybe").drop("maybe"), marked.filter("maybe").drop("maybe")


def without_keys(rows: DataFrame, keys: DataFrame, key: str, *more: str) -> DataFrame:
    """``rows`` whose 64-bit ``key`` and ``more`` columns are not among ``keys`` (a table). Rows whose slot is empty pass straight through;
    only the others shuffle."""
    passed, maybe = split_by_keys(rows, keys, key)
    drop = keys.select(key, *more).distinct().alias("gone")
    same = F.col(f"kept.{key}") == F.col(f"gone.{key}")
    for name in more:
        same = same & F.col(f"kept.{name}").eqNullSafe(F.col(f"gone.{name}"))
    return passed.unionByName(maybe.alias("kept").join(drop, same, "left_anti").select(*passed.columns))


def key_table(keys: DataFrame, key: str) -> np.ndarray:
    """The table of a column of 64-bit keys as bytes on the driver: ``2**(MOST_ARRAY_BITS - 3)`` at most, whatever the number of keys."""
    bits = slot_bits_for(keys.count(), MOST_ARRAY_BITS)
    found = bit_words(keys.select(slot_of(key, bits).alias("slot"))).toArrow()
    words = np.zeros(1 << (bits - 6), np.uint64)
    words[found["word"].to_numpy()] = found["bits"].to_numpy().view(np.uint64)
    return words.view(np.uint8)


def in_table(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whether the slots of the 64-bit ``keys`` are set."""
    slot = keys.view(np.uint64) & np.uint64(8 * len(table) - 1)
    return (table[(slot >> np.uint64(3)).astype(np.int64)] >> (slot & np.uint64(7)).astype(np.uint8)) & np.uint8(1) == 1
