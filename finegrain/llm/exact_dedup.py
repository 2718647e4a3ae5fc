"""Exact duplicate removal: a two-pass Bloom filter finds possibly repeated hashes, and only those rows shuffle.

Every text's SHA-256 is staged once, with its id. Pass 1 counts the rows of each slot of a first hash function and keeps the slots with two
or more as a bit table; pass 2 does the same with a second function for those rows only that pass 1 could not prove unique. What
both tables leave is grouped by the full SHA-256. The groups with two rows or more make the bit table that the documents themselves
are tested against: a document that misses it passes straight through, the others are joined with their group. A
false positive costs a shuffled row, never a wrong result.

The only thing that the filter itself moves is a slot's number and count, some 16 bytes a document (pass 1), and no text. The tables
follow the number of rows, eight slots each, up to 2**26 slots: 2**20 broadcast words at most. Beyond some 10**7 rows the
hashes' table fills and narrow rows of id and hash shuffle instead; documents still pass unless their slot holds a repeated text.

Defined results: a null text counts as empty, so all null and empty texts are equal. Of equal texts the row with the
smallest id stays (null ids come last); of rows that agree in text and id exactly one stays, whichever partitions they are read in. An
empty table gives an empty table. Input columns are kept under any names; the columns added here replace input columns of the same name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.llm.filters import bit_words, slot_bits_for, slot_of, tested
from finegrain.llm.rows import column, packed, unpacked
from finegrain.operators.skew import join_group_facts
from finegrain.sources.staging import staged

OWN = ("text_sha256", "keep_id", "group_size", "kept")


def normalised(text: str = "text") -> Column:
    """The text with every run of white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(column(text), F.lit("")), r"[\x20\x09-\x0D]+", " ")


def fingerprint(text: str = "text") -> Column:
    """Lower-case hexadecimal SHA-256 of the normalised text."""
    return F.sha2(F.encode(normalised(text), "UTF-8"), 256)


def _slot(sha: str, function: int, slot_bits: int) -> Column:
    """The slot of a hash under one of the filter's functions: its own 15 hexadecimal digits of the SHA-256."""
    return slot_of(F.conv(F.substring(sha, 1 + 15 * function, 15), 16, 10).cast("long"), slot_bits)


def repeated_words(rows: DataFrame, function: int, slot_bits: int) -> DataFrame:
    """The words of the slots that two rows or more fall into."""
    return bit_words(rows.select(_slot("sha", function, slot_bits).alias("slot")).groupBy("slot").count().filter("count > 1"))


def repeated_groups(hashes: DataFrame, slot_bits: int) -> DataFrame:
    """Staged ``(sha, size, none, first_id, ties)`` of the texts that stand in two rows or more of ``hashes`` (id, sha): rows, whether all ids are
    null, the least id and how many rows have it."""
    maybe = hashes
    for function in range(2):
        maybe = tested(maybe, _slot("sha", function, slot_bits), repeated_words(maybe, function, slot_bits)).filter("maybe").drop("maybe")
    # equal texts of one id first, so that neither step meets all rows of a frequent text
    by_id = maybe.groupBy("sha", "id").agg(F.count("*").alias("n"))
    groups = by_id.groupBy("sha").agg(F.sum("n").alias("size"), F.min(F.struct(F.col("id").isNull().alias("none"), "id", "n")).alias("first"))
    kept = groups.filter("size > 1").select("sha", "size", F.col("first.none").alias("none"), F.col("first.id").alias("first_id"), F.col("first.n").alias("ties"))
    return staged(kept, "repeated-groups")


def mark_copies(rows: DataFrame, groups: DataFrame, total: int) -> DataFrame:
    """``rows`` (id, sha and others) with ``keep_id``, ``group_size`` and ``kept``.

    Nothing here depends on where a row was read: of rows that agree in text and id, which only repeated ids have, the one
    that stays is chosen among rows written down for that.
    """
    bits = slot_bits_for(groups.count())
    marked = tested(rows, _slot("sha", 0, bits), bit_words(groups.select(_slot("sha", 0, bits).alias("slot"))))
    facts = [F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept")]
    single = marked.filter("not maybe").drop("maybe").select("*", *facts)
    # the salt decides only which task meets a row
    salted = marked.filter("maybe").drop("maybe").withColumn("spread", F.monotonically_increasing_id())
    met = join_group_facts(salted, groups, "sha", "size", total, "spread").drop("spread")
    grouped, least = F.col("size").isNotNull(), F.col("id").eqNullSafe(F.col("first_id"))
    met = met.select(
        *rows.columns,
        F.when(grouped, F.col("first_id")).otherwise(F.col("id")).alias("keep_id"),
        F.coalesce("size", F.lit(1)).cast("long").alias("group_size"),
        (~grouped | least).alias("kept"),
        (grouped & least & (F.col("ties") > 1)).alias("tied"),
    )
    names = [*rows.columns, "keep_id", "group_size", "kept"]
    if not groups.filter("ties > 1").limit(1).count():
        return single.unionByName(met.select(*names))
    tied = staged(met.filter("tied").drop("tied").withColumn("at", F.monotonically_increasing_id()), "tied-rows")
    first = tied.groupBy("sha").agg(F.min("at").alias("least_at"), F.count("*").alias("ties"))
    chosen = join_group_facts(tied, staged(first, "tied-groups"), "sha", "ties", total, "at").withColumn("kept", F.col("at") == F.col("least_at"))
    return single.unionByName(met.filter("not tied").select(*names)).unionByName(chosen.select(*names))


def _hashes(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    return staged(docs.select(column(id_col).alias("id"), fingerprint(text).alias("sha")), "hashes")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text: str = "text", slot_bits: int | None = None) -> DataFrame:
    """All rows and columns of ``docs`` (a table: it is read twice, in any partitions) with ``text_sha256``, ``keep_id``,
    ``group_size`` and ``kept``."""
    docs = docs.drop(*(c for c in OWN if c not in (id_col, text)))
    hashes = _hashes(docs, id_col, text)
    total = hashes.count()
    groups = repeated_groups(hashes, slot_bits or slot_bits_for(total))
    rows = packed(docs, id=column(id_col), sha=fingerprint(text))
    marked = mark_copies(rows, groups, total).withColumn("text_sha256", F.col("sha"))
    return unpacked(marked, docs.columns, *(c for c in OWN if c not in docs.columns))


def exact_dedup_digest(docs: DataFrame, id_col: str = "doc_id", text: str = "text", slot_bits: int | None = None) -> DataFrame:
    """As :func:`exact_dedup`, for callers that need the decisions and not the texts: the texts are read once."""
    hashes = _hashes(docs, id_col, text)
    total = hashes.count()
    marked = mark_copies(hashes, repeated_groups(hashes, slot_bits or slot_bits_for(total)), total)
    return marked.select(F.col("id").alias(id_col), F.col("sha").alias("text_sha256"), "keep_id", "group_size", "kept")
